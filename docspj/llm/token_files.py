"""Token-ID files: flat unsigned integers and 64-bit document offsets, one pair of files a range of document ids.

`<shard>.bin` holds the ids of a shard's documents one after another, two bytes each (four where the vocabulary needs it), little-endian.
`<shard>.idx` holds, as 64-bit unsigned integers: the width of an id in bytes, the number of documents, of documents with a
null id (they come first), then documents + 1 offsets in ids, then the document ids. Shards are in ascending order of document
id; a shard's base, the ids before it, is the prefix sum of the shards' lengths. Files are written under a name of the
attempt and then renamed, so a task that runs again leaves the same files.
"""

from __future__ import annotations

import json
import os
import re
import uuid
import zlib
from collections.abc import Iterator
from functools import lru_cache
from itertools import compress
from operator import not_

import numpy as np
import pyarrow as pa
import pyarrow.fs
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from docspj.llm.common import only, scratch_path, slices

_HEAD = 3
_TOUCHING = re.compile(r"\s\s")
#: White space other than blanks and line feeds, which few texts hold.
_OTHER_SPACE = [c for c in map(chr, range(0x10000)) if c.isspace() and c not in " \n"]
_LATIN_END, _MARKS = "\u0250", (".", ",")
#: Byte-level vocabularies write bytes that are no visible Latin-1 letter as letters from U+0100 on, in order.
_VISIBLE = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
_BYTE_LETTERS = {b: chr(256 + i) for i, b in enumerate(b for b in range(256) if b not in _VISIBLE)}


def cuts_at_blanks(settings: dict) -> bool:
    """Whether a tokenizer's settings are those that pieces may be cut for: bytes merged by rank within the byte-level splitting, no more and no less."""
    split, model = settings.get("pre_tokenizer") or {}, settings.get("model") or {}
    plain = split.get("type") == "ByteLevel" and split.get("use_regex") is True and split.get("add_prefix_space") is False and settings.get("normalizer") is None
    whole = not any(model.get(k) for k in ("dropout", "continuing_subword_prefix", "end_of_word_suffix", "ignore_merges", "byte_fallback"))
    # An added token with a blank or line feed in it, or one that takes blanks beside it, could be cut in two.
    added = all(not re.search(r"\s", t["content"]) and not (t["lstrip"] or t["rstrip"] or t["single_word"]) for t in settings.get("added_tokens") or [])
    return plain and whole and added and model.get("type") == "BPE"


def touching(text: str) -> bool:
    """Whether white space touches white space: _TOUCHING, by searches for single strings where a text holds blanks and line feeds alone."""
    if "  " in text or " \n" in text or "\n " in text or "\n\n" in text:
        return True
    return any(c in text for c in _OTHER_SPACE) and _TOUCHING.search(text) is not None


@lru_cache(1)
def loaded(path: str, changed: int) -> tuple:
    """A tokenizer file, as it was then: the tokenizer, whether pieces may be cut for it, each id packed, each id's length in bytes. A worker serves many tasks and reads it once."""
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(path)
    special = tokenizer.get_added_tokens_decoder()
    names = [tokenizer.id_to_token(i) or "" for i in range(tokenizer.get_vocab_size(True))]
    packed = [np.array([i], "<u4").tobytes() for i in range(len(names))]
    return tokenizer, cuts_at_blanks(json.loads(tokenizer.to_str())), packed, np.array([len(n.encode()) if i in special else len(n) for i, n in enumerate(names)])


class CachingEncoder:
    """Whole texts to ids with the tokenizers library, which sees a piece of text once while it is remembered.

    A text is cut before each blank and line feed that follows something else than white space. There the byte-level
    vocabulary's splitting never joins what the cut parts, so a piece's ids do not depend on what is around it. Pieces are
    remembered in two generations of bounded size: what the older one answers moves to the younger. A text in which white
    space touches white space is encoded as it is; so is every text where the file's splitting is not that byte-level one.
    """

    def __init__(self, path: str, end_id: int | None, most: int = 600_000):
        self.young, self.old, self.most = {}, {}, most
        self.tokenizer, self.cuts, self.packed, self.lengths = loaded(path, os.stat(path).st_mtime_ns)
        self.merges = self.tokenizer.model.tokenize
        self.end = b"" if end_id is None else np.array([end_id], "<u4").tobytes()
        self.marks = {m: self._word(m) for m in (*_MARKS, "\n")} if self.cuts else {}
        self.width = 2 if max(self.tokenizer.get_vocab_size(True) - 1, end_id or 0) < 1 << 16 else 4

    def _ids(self, text: str) -> bytes:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def _word(self, word: str) -> bytes:
        """Ids of one piece of the vocabulary's own splitting, straight from its merges."""
        packed = self.packed
        return b"".join([packed[t.id] for t in self.merges(word.encode().decode("latin-1").translate(_BYTE_LETTERS))])

    def _blank_word(self, word: str) -> bytes:
        """Ids of a Latin word after a blank."""
        if word.isascii():
            packed = self.packed
            return b"".join([packed[t.id] for t in self.merges(_BYTE_LETTERS[32] + word)])
        return self._word(f" {word}")

    def _pieces(self, new: list[str]) -> dict[str, bytes]:
        """Ids of pieces that were not seen yet.

        Latin words, alone, after a line feed or before a full stop or comma, are pieces of the vocabulary's own splitting. All others go in one
        text, whose ids' lengths in bytes say where each piece ends.
        """
        found, rest, packed, merges, blank = {}, [], self.packed, self.merges, _BYTE_LETTERS[32]
        for p in new:
            if p.isascii() and p.isalpha():
                found[p] = b"".join([packed[t.id] for t in merges(blank + p)])
            elif p.isalpha() and max(p) < _LATIN_END:
                found[p] = self._word(f" {p}")
            elif p[-1:] in _MARKS and p[:-1].isalpha() and (p.isascii() or max(p) < _LATIN_END):
                stem = p[:-1]
                known = self.young.get(stem) or found.get(stem) or self.old.get(stem)
                if known is None:
                    known = found[stem] = self._blank_word(stem)
                found[p] = known + self.marks[p[-1]]
            elif p[:1] == "\n" and p[1:].isalpha() and (p.isascii() or max(p) < _LATIN_END):
                found[p] = self.marks["\n"] + self._word(p[1:])
            elif not p or p[-1].isspace():
                found[p] = self._ids(p if p[:1] == "\n" else f" {p}")
            else:
                rest.append(p)
        if rest:
            plain = [p if p[0] == "\n" else f" {p}" for p in rest]
            ids = np.array(self.tokenizer.encode_batch_fast(["".join(plain)], add_special_tokens=False)[0].ids, "<u4")
            cuts = np.searchsorted(np.cumsum(self.lengths[ids]), np.cumsum([len(p.encode()) for p in plain])) + 1
            raw, at = ids.tobytes(), 0
            for p, cut in zip(rest, (cuts * 4).tolist(), strict=True):
                found[p] = raw[at:cut]
                at = cut
        return found

    def encode(self, text: str | None) -> bytes:
        """The text's ids, and the end id, as 32-bit unsigned little-endian integers."""
        if not text:
            return self.end
        if not self.cuts or touching(text):
            return self._ids(text) + self.end
        head, *parts = text.replace("\n", " \n").split(" ")
        first = self._ids(head) if head else b""
        if len(self.young) > self.most:
            self.old, self.young = self.young, {}
        young, old, new = self.young, self.old, []
        for p in set(compress(parts, map(not_, map(young.get, parts)))):
            if p in old:
                young[p] = old[p]
            else:
                new.append(p)
        young.update(self._pieces(new))
        result = first + b"".join(map(young.__getitem__, parts)) + self.end
        for p in new:
            if len(p) > 64:
                del young[p]
        return result


def _open(folder: str) -> tuple[pa.fs.FileSystem, str]:
    return pa.fs.FileSystem.from_uri(folder)


def write_token_files(docs: DataFrame, tokenizer_path: str, folder: str, end_id: int | None = 2, rows_a_shard: int = 20_000, remembered: int = 600_000, bytes_a_shard: int = 32 << 20) -> DataFrame:
    """Write docs(doc_id, text) to folder in ascending order of doc_id, null ids first; (shard, docs, ids) of each shard.

    There are as many shards as the rows, and the characters, of all documents need at `rows_a_shard` and `bytes_a_shard` each.

    Null and empty texts are the end id alone. Rows that repeat an id are each written, in the order of their texts. Without rows
    there are no shards. The folder must be one that all executors share, of a kind pyarrow opens.
    """
    docs = only(docs, ["doc_id", "text"])
    rows, chars = docs.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()
    parts = max(1, -(-rows // rows_a_shard), -(-chars // bytes_a_shard))
    ordered = docs.repartitionByRange(max(parts, docs.sparkSession.sparkContext.defaultParallelism), F.col("doc_id").asc_nulls_first(), F.xxhash64("text")).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), F.xxhash64("text"), "text")

    def of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, shard, counts, keys, nulls = None, TaskContext.get().partitionId(), [], [], 0
        system, root = _open(folder)
        target, attempt = f"{root}/{shard:08d}", uuid.uuid4().hex
        out = None
        for batch in slices(batches):
            if not batch.num_rows:
                continue
            if encoder is None:
                encoder = CachingEncoder(tokenizer_path, end_id, remembered)
                system.create_dir(root, recursive=True)
                out = system.open_output_stream(f"{target}.bin.{attempt}")
            for key, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ids = encoder.encode(text.as_py())
                nulls += key is None
                counts.append(len(ids) // 4), keys.append(key or 0)
                out.write(np.frombuffer(ids, "<u4").astype(f"<u{encoder.width}").tobytes())
        if out is not None:
            out.close()
            index = np.concatenate([[encoder.width, len(counts), nulls, 0], np.cumsum(counts)]).astype("<u8")
            with system.open_output_stream(f"{target}.idx.{attempt}") as f:
                f.write(index.tobytes() + np.array(keys, "<i8").tobytes())
            for kind in ("bin", "idx"):
                # Some stores don't move onto a file that is there, as an attempt before may have left it.
                if system.get_file_info(f"{target}.{kind}").type != pa.fs.FileType.NotFound:
                    system.delete_file(f"{target}.{kind}")
                system.move(f"{target}.{kind}.{attempt}", f"{target}.{kind}")
            yield pa.RecordBatch.from_pydict({"shard": pa.array([shard], pa.int64()), "docs": pa.array([len(counts)], pa.int64()), "ids": pa.array([sum(counts)], pa.int64())})

    return ordered.mapInArrow(of, "shard long, docs long, ids long")


def read_token_files(shards: DataFrame, folder: str) -> DataFrame:
    """(doc_id, shard, start, n_tokens, ids_crc32) of each document in the files of shards(shard, ids); nothing else is read.

    start counts the ids of all documents before; ids_crc32 is of the ids as 32-bit little-endian unsigned integers.
    """
    before = Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    based = shards.select("shard", F.coalesce(F.sum("ids").over(before), F.lit(0)).alias("base"))
    spread = based.repartition(max(2, min(2000, based.sparkSession.sparkContext.defaultParallelism * 4)), "shard")

    def of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        system, root = _open(folder)
        for batch in batches:
            for shard, base in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                path = f"{root}/{shard:08d}"
                if isinstance(system, pa.fs.LocalFileSystem):
                    index, raw = np.memmap(f"{path}.idx", "<u8", "r"), np.memmap(f"{path}.bin", np.uint8, "r")
                else:
                    index, raw = (np.frombuffer(system.open_input_stream(f"{path}.{k}").read(), t) for k, t in (("idx", "<u8"), ("bin", np.uint8)))
                width, count, nulls = (int(x) for x in index[:_HEAD])
                offsets = index[_HEAD : _HEAD + count + 1].astype(np.int64)
                keys, ids = index[_HEAD + count + 1 :].view("<i8"), raw.view(f"<u{width}")
                for low in range(0, count, 4096):
                    high = min(count, low + 4096)
                    sums = [zlib.crc32(ids[offsets[d] : offsets[d + 1]].astype("<u4").tobytes()) for d in range(low, high)]
                    yield pa.RecordBatch.from_pydict(
                        {
                            "doc_id": pa.array(np.array(keys[low:high]), pa.int64(), mask=np.arange(low, high) < nulls),
                            "shard": pa.array(np.full(high - low, shard), pa.int64()),
                            "start": pa.array(base + offsets[low:high]),
                            "n_tokens": pa.array(np.diff(offsets[low : high + 1])),
                            "ids_crc32": pa.array(sums, pa.int64()),
                        }
                    )

    return spread.mapInArrow(of, "doc_id long, shard long, start long, n_tokens long, ids_crc32 long")


def tokenise(docs: DataFrame, tokenizer_path: str, folder: str | None = None, end_id: int | None = 2, **options) -> DataFrame:
    """Write docs as token files, to a folder of the shared one if none is given, and return what the files hold of each document."""
    folder = folder or scratch_path(docs.sparkSession, "tokens")
    written = write_token_files(docs, tokenizer_path, folder, end_id, **options)
    path = scratch_path(docs.sparkSession, "shards")
    written.write.parquet(path)
    shards = docs.sparkSession.read.schema(written.schema).parquet(path)
    return read_token_files(shards, folder)
