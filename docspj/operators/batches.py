"""Segments, hashed vectors and radii in Arrow batches: what operators.segments and functions.text say as Columns, for many documents.

Documents share words and whole sentences. A task keeps what it has made of them, up to MOST of each, so a sentence that many documents hold
is cut into words and hashed once a task; distances of a batch's vectors from all centres are one sum over their places.
"""

from __future__ import annotations

import hashlib
import math
import re
import unicodedata
from collections import Counter
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from docspj.functions.text import _BLANKS, DIMENSIONS, STOP_WORDS

#: Words, and sentences, that a task remembers; then it begins anew.
MOST = 200_000
#: Texts that a worker keeps from one task to the next, and up to MOST pairs of them.
KEPT = 50_000
#: Documents a piece, so that what a worker holds is bounded.
ROWS = 512
_ENDS, _LINES, _TOKEN, _DIGITS = re.compile(r"([.!?])[ \t\n\x0b\f\r]+"), re.compile(r"\n+"), re.compile(r"[^ \t\n\x0b\f\r]+"), re.compile(r"[0-9]+")
_STOP = frozenset(STOP_WORDS)
_MAP = pa.map_(pa.int32(), pa.int32())


def sentences(text: str) -> list[str]:
    return [s for s in (x.strip(_BLANKS) for x in _LINES.split(_ENDS.sub(r"\1\n", text))) if s]


def _inner(c: str) -> bool:
    return c == "#" or unicodedata.category(c)[0] in "LN"


class Hasher:
    """Vectors of texts: (tokens, buckets, counts, squared length), remembered by text."""

    def __init__(self, d: int = DIMENSIONS, most: int = MOST):
        self.d, self.most, self.words, self.texts, self.tables = d, most, {}, {}, {}

    def bucket(self, token: str) -> int:
        """The bucket of a token's word; -1 of none."""
        found = self.words.get(token)
        if found is None:
            w = _DIGITS.sub("#", token.lower())
            low, high = 0, len(w)
            while low < high and not _inner(w[low]):
                low += 1
            while low < high and not _inner(w[high - 1]):
                high -= 1
            w = w[low:high]
            found = -1 if not w or w in _STOP else int(hashlib.md5(w.encode()).hexdigest()[:7], 16) % self.d
            if len(self.words) >= self.most:
                self.words.clear()
            self.words[token] = found
        return found

    def __call__(self, text: str) -> tuple[int, list[int], list[int], int]:
        found = self.texts.get(text)
        if found is None:
            tokens = _TOKEN.findall(text)
            found = (len(tokens), *self.packed(Counter(b for b in map(self.bucket, tokens) if b >= 0)))
            if len(self.texts) >= self.most:
                self.texts.clear()
            self.texts[text] = found
        return found

    def table(self, text: str) -> tuple[dict[int, int], int]:
        """A text's counts by bucket, and their squared length."""
        found = self.tables.get(text)
        if found is None:
            _, places, values, square = self(text)
            if len(self.tables) >= self.most:
                self.tables.clear()
            found = self.tables[text] = (dict(zip(places, values, strict=True)), square)
        return found

    @staticmethod
    def packed(counts: Counter) -> tuple[list[int], list[int], int]:
        places = sorted(counts)
        values = [counts[p] for p in places]
        return places, values, sum(v * v for v in values)


_held: dict[int, tuple[Hasher, dict]] = {}


def _kept(d: int) -> tuple[Hasher, dict]:
    """The worker's own hasher, and what it knows of which sentences are near: what documents share is made once a worker."""
    return _held.setdefault(d, (Hasher(d, KEPT), {}))


def _maps(vectors: list[tuple]) -> pa.Array:
    """map<int,int> of (buckets, counts) pairs."""
    offsets = np.zeros(len(vectors) + 1, np.int32)
    np.cumsum([len(v[0]) for v in vectors], out=offsets[1:])
    flat = lambda j: pa.array([x for v in vectors for x in v[j]], pa.int32())
    return pa.MapArray.from_arrays(pa.array(offsets), flat(0), flat(1))


def _pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for low in range(0, batch.num_rows, ROWS):
            yield batch.slice(low, ROWS)


def embedded(rows: DataFrame, text: str, d: int = DIMENSIONS) -> DataFrame:
    """rows with vec and n2 of a text column: functions.text.embed and norm2. A null text's are null."""
    at = rows.columns.index(text)

    def of(batches):
        hasher = Hasher(d)
        for batch in _pieces(batches):
            texts = batch.column(at).to_pylist()
            made = [([], [], 0) if t is None else hasher(t)[1:] for t in texts]
            vecs, squares = _maps(made), pa.array([None if t is None else m[2] for t, m in zip(texts, made, strict=True)], pa.int64())
            if None in texts:
                vecs = pa.array([None if t is None else list(zip(m[0], m[1], strict=True)) for t, m in zip(texts, made, strict=True)], _MAP)
            yield pa.RecordBatch.from_arrays([*batch.columns, vecs, squares], [*batch.schema.names, "vec", "n2"])

    return rows.mapInArrow(of, f"{_declared(rows)}, vec map<int,int>, n2 bigint")


def _declared(rows: DataFrame) -> str:
    return ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields)


def led(docs: DataFrame, d: int = DIMENSIONS) -> DataFrame:
    """(corpus, doc_key, vecs, n2s): of each document the vector of its opening sentence, operators.segments.summarise in mode lead; a null text's is that of no word."""

    def of(batches):
        hasher = Hasher(d)
        for batch in _pieces(batches):
            made = [hasher(next(iter(sentences(t or "")), ""))[1:] for t in batch.column(2).to_pylist()]
            each = pa.array(np.arange(len(made) + 1, dtype=np.int32))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.ListArray.from_arrays(each, _maps(made)), pa.ListArray.from_arrays(each, pa.array([m[2] for m in made], pa.int64()))], ["corpus", "doc_key", "vecs", "n2s"])

    rows = docs.select("corpus", "doc_key", "text")
    return rows.mapInArrow(of, f"{_declared(rows.select('corpus', 'doc_key'))}, vecs array<map<int,int>>, n2s array<bigint>")


def segmented(docs: DataFrame, sim_threshold: float = 0.25, max_tokens: int = 200, d: int = DIMENSIONS, opening: bool = False) -> DataFrame:
    """(corpus, doc_key, seg_no, text, n_tokens, first_sent, last_sent, vec, n2): operators.segments.segment, mode previous, with vectors.

    With opening, lead and lead_n2 come in their place: a document's first row has the vector of its opening sentence as `led` makes it, the others nulls. A document
    without a sentence then has one row, of no segment. Both levels are so made of one pass over the texts, and segments' vectors are left to be made of theirs.
    """
    far = (2 - 2 * sim_threshold) ** 0.5
    rows = docs.select("corpus", "doc_key", "text")

    def of(batches):
        hasher, close = _kept(d)

        def near(a: str, b: str) -> bool:
            found = close.get((a, b))
            if found is None:
                (own, a2), (other, b2) = hasher.table(a), hasher.table(b)
                inner = sum([own[p] * other[p] for p in own.keys() & other.keys()])
                cos = inner / math.sqrt(float(a2) * float(b2)) if a2 and b2 else 0.0
                found = math.sqrt(max(0.0, 2 - 2 * cos)) <= far
                if len(close) >= MOST:
                    close.clear()
                close[a, b] = found
            return found

        for batch in _pieces(batches):
            of_row, numbers, texts, tokens, first, last, vectors = [], [], [], [], [], [], []

            def closed(row: int, number: int, begin: int, own: list[str], n: int) -> None:
                of_row.append(row), numbers.append(number), tokens.append(n), first.append(begin), last.append(begin + len(own) - 1)
                if opening:
                    texts.append(" ".join(own)), vectors.append(hasher(own[0])[1:] if number == 0 else None)
                elif len(own) == 1:
                    texts.append(own[0]), vectors.append(hasher(own[0])[1:])
                else:
                    counts: Counter = Counter()
                    for s in own:
                        _, places, values, _ = hasher(s)
                        for p, v in zip(places, values, strict=True):
                            counts[p] += v
                    texts.append(" ".join(own)), vectors.append(hasher.packed(counts))

            for row, text in enumerate(batch.column(2).to_pylist()):
                own, n, begin, number = [], 0, 0, 0
                for i, s in enumerate(sentences(text) if text else ()):
                    size = hasher(s)[0]
                    if own and n + size <= max_tokens and near(own[-1], s):
                        own.append(s)
                        n += size
                        continue
                    if own:
                        closed(row, number, begin, own, n)
                        number += 1
                    own, n, begin = [s], size, i
                if own:
                    closed(row, number, begin, own, n)
                elif opening:
                    for column, value in ((of_row, row), (numbers, None), (texts, None), (tokens, None), (first, None), (last, None), (vectors, hasher("")[1:])):
                        column.append(value)
            taken = pa.array(of_row, pa.int32())
            made = [batch.column(0).take(taken), batch.column(1).take(taken), pa.array(numbers, pa.int32()), pa.array(texts, pa.string()), *(pa.array(x, pa.int32()) for x in (tokens, first, last))]
            vecs = pa.array([None if v is None else list(zip(v[0], v[1], strict=True)) for v in vectors], _MAP) if opening else _maps(vectors)
            yield pa.RecordBatch.from_arrays([*made, vecs, pa.array([None if v is None else v[2] for v in vectors], pa.int64())], ["corpus", "doc_key", "seg_no", "text", "n_tokens", "first_sent", "last_sent", *names])

    names = ("lead", "lead_n2") if opening else ("vec", "n2")
    return rows.mapInArrow(of, f"{_declared(rows.select('corpus', 'doc_key'))}, seg_no int, text string, n_tokens int, first_sent int, last_sent int, {names[0]} map<int,int>, {names[1]} bigint")


def distances(vecs: pa.Array, squares: np.ndarray, centres: np.ndarray) -> np.ndarray:
    """functions.text.distance_to of a batch's maps from each of some centres: a row a map, a column a centre."""
    offsets = np.asarray(vecs.offsets)
    keys, items = np.asarray(vecs.keys), np.asarray(vecs.items).astype(float)
    low, high = int(offsets[0]), int(offsets[-1])
    inner, full = np.zeros((len(squares), len(centres))), np.diff(offsets) > 0
    if high > low:
        inner[full] = np.add.reduceat(items[low:high, None] * centres.T[keys[low:high]], offsets[:-1][full] - low, axis=0)
    long = squares > 0
    inner = np.where(long[:, None], inner / np.sqrt(np.where(long, squares, 1.0))[:, None], 0.0)
    return np.sqrt(np.maximum(0.0, long[:, None] + (centres**2).sum(1)[None] - 2 * inner))


def near_texts(segments: DataFrame, asked: Sequence[tuple[str, Sequence[Sequence[float]], float]], d: int = DIMENSIONS) -> DataFrame:
    """near of segments(doc_key, seg_no, text, n_tokens) whose vectors are the hashed words of their texts: a text that many hold is hashed and measured once a task."""
    centres = np.array([c for _, own, _ in asked for c in own], float)
    bounds = np.cumsum([0, *(len(own) for _, own, _ in asked)])

    def of(batches):
        hasher, known = Hasher(d, KEPT), {}

        def judge(texts: list[str]) -> None:
            for at in range(0, len(texts), 4096):
                some = texts[at : at + 4096]
                made = [hasher(t)[1:] for t in some]
                found = distances(_maps(made), np.array([m[2] for m in made], float), centres)
                flags = [found[:, low:high].min(1, initial=np.inf) <= radius for low, high, (_, _, radius) in zip(bounds, bounds[1:], asked, strict=False)]
                known.update(zip(some, zip(*(f.tolist() for f in flags), strict=True), strict=True))

        for batch in batches:
            coded = batch.column(2).dictionary_encode()
            own = coded.dictionary.to_pylist()
            if len(known) + len(own) > MOST:
                known.clear()
            judge([t for t in own if t not in known])
            # The last row stands for a null text, which is near nothing.
            judged = np.array([*(known[t] for t in own), (False,) * len(asked)], bool).reshape(len(own) + 1, len(asked))
            flags = judged[coded.indices.fill_null(len(own)).to_numpy(zero_copy_only=False)]
            hit = np.flatnonzero(flags.any(1))
            if len(hit):
                yield pa.RecordBatch.from_arrays([*(batch.column(j).take(pa.array(hit)) for j in range(4)), *(pa.array(f) for f in flags[hit].T.copy())], [*batch.schema.names[:4], *(f"near_{n}" for n, _, _ in asked)])

    rows = segments.select("doc_key", "seg_no", "text", "n_tokens")
    return rows.mapInArrow(of, ", ".join([_declared(rows), *(f"near_{n} boolean" for n, _, _ in asked)]))


def near(segments: DataFrame, asked: Sequence[tuple[str, Sequence[Sequence[float]], float]]) -> DataFrame:
    """Of segments(doc_key, seg_no, text, n_tokens, vec, n2) those within the radius of a centre of some (name, centres, radius), with near_<name>."""
    centres = np.array([c for _, own, _ in asked for c in own], float)
    bounds = np.cumsum([0, *(len(own) for _, own, _ in asked)])

    def of(batches):
        for whole in batches:
            for at in range(0, whole.num_rows, 4096):
                batch = whole.slice(at, 4096)
                vecs, squares = batch.column(4), batch.column(5)
                known = vecs.is_valid().to_numpy(zero_copy_only=False) & squares.is_valid().to_numpy(zero_copy_only=False)
                found = distances(vecs, squares.fill_null(0).to_numpy(zero_copy_only=False).astype(float), centres)
                flags = [(found[:, low:high].min(1, initial=np.inf) <= radius) & known for low, high, (_, _, radius) in zip(bounds, bounds[1:], asked, strict=False)]
                hit = np.flatnonzero(np.any(flags, axis=0))
                if len(hit):
                    yield pa.RecordBatch.from_arrays([*(batch.column(j).take(pa.array(hit)) for j in range(4)), *(pa.array(f[hit]) for f in flags)], [*batch.schema.names[:4], *(f"near_{n}" for n, _, _ in asked)])

    rows = segments.select("doc_key", "seg_no", "text", "n_tokens", "vec", "n2")
    return rows.mapInArrow(of, ", ".join([_declared(rows.select("doc_key", "seg_no", "text", "n_tokens")), *(f"near_{n} boolean" for n, _, _ in asked)]))
