"""MinHash near-duplicate groups: many universal hash minima, banding, signature check, exact check, components.

A document's set is its distinct word shingles. Rows with the same set form one class and only the class's least id goes on.
144 multiply-add-shift minima are cut into 36 bands of 4, so a pair of similarity 0.75 shares no band with a chance of 1e-6.
Documents that share a band with another get a finer signature, the least shingle of each of 4096 hash ranges, which decides what
is worth an exact check; of all buckets two documents share, only the first band's looks at them. Within a band's bucket no pairs are listed: first every member is held against the bucket's least id;
after components are formed, buckets that still hold several components are searched in blocks for untested pairs across
components, and a block returns a number of pairs linear in its size; this goes on until none is left, so no link is lost to
the number. A tested pair is remembered at one of its two documents, never at a bucket's least id, so that what a row carries grows with the
bands and blocks of its own document alone. A bucket of n members, all unlike, ships n * n / block signatures: the worst case.
"""

from __future__ import annotations

from collections import OrderedDict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from docspj.llm.common import only, scratch, slices
from docspj.llm.components import connected_components
from docspj.llm.shingles import mix, overlap, shingle_sets


@dataclass(frozen=True)
class MinHashParams:
    """percent: least share of common shingles. deviations: how many standard deviations a fine signature may fall short of it."""

    width: int = 5
    percent: int = 75
    bands: int = 36
    rows: int = 4
    deviations: float = 5.0
    fine_bits: int = 12
    block: int = 2048
    partners: int = 64
    seed: int = 77
    most_broadcast_ids: int = 1_000_000

    @property
    def hashes(self) -> int:
        return self.bands * self.rows

    def family(self) -> tuple[np.ndarray, np.ndarray]:
        rng = np.random.default_rng(self.seed)
        odd = (rng.integers(0, 2**63, self.hashes, dtype=np.uint64) << np.uint64(1)) | np.uint64(1)
        return odd, rng.integers(0, 2**63, self.hashes, dtype=np.uint64)


def band_hashes(elements: np.ndarray, odd: np.ndarray, shift: np.ndarray, rows: int) -> np.ndarray:
    """Minimum of each universal hash over the elements, upper 32 bits, and one hash of each band's minima."""
    best = np.full(len(odd), np.uint64(2**64 - 1))
    for at in range(0, len(elements), 1024):
        part = elements[None, at : at + 1024] * odd[:, None]
        part += shift[:, None]
        np.minimum(best, part.min(axis=1), out=best)
    best = (best >> np.uint64(32)).reshape(-1, rows)
    out = np.zeros(len(best), np.uint64)
    for k in range(rows):
        out = mix(out + best[:, k])
    return out.astype("<u8")


def digest(elements: np.ndarray) -> tuple[int, int]:
    """128 bits of a set."""
    return int(elements.sum(dtype=np.uint64).view(np.int64)), int(mix(elements ^ np.uint64(0x5DEECE66D)).sum(dtype=np.uint64).view(np.int64))


def _features(docs: DataFrame, p: MinHashParams) -> DataFrame:
    """(id, n_shingles, low, high, sig) a document; low and high, a digest of the set, and sig are null for an empty set."""
    odd, shift = p.family()

    def of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            sizes, lows, highs, sigs = [], [], [], []
            for found in shingle_sets(batch.column(1).cast(pa.binary()).to_pylist(), p.width):
                sizes.append(len(found))
                if len(found):
                    low, high = digest(found)
                    lows.append(low), highs.append(high)
                    sigs.append(band_hashes(found, odd, shift, p.rows).tobytes())
                else:
                    lows.append(None), highs.append(None), sigs.append(None)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(sizes, pa.int64()), pa.array(lows, pa.int64()), pa.array(highs, pa.int64()), pa.array(sigs, pa.binary())],
                names=["id", "n_shingles", "low", "high", "sig"],
            )

    return docs.mapInArrow(of, "id long, n_shingles long, low long, high long, sig binary")


def fine_signature(elements: np.ndarray, bits: int) -> np.ndarray:
    """A byte of the least of the sorted elements in each of 2**bits ranges of their values; 0 where a range is empty."""
    ranges = (elements >> np.uint64(64 - bits)).astype(np.int64)
    first = np.flatnonzero(np.diff(ranges, prepend=-1))
    out = np.zeros(1 << bits, np.uint8)
    out[ranges[first]] = (elements[first] % np.uint64(255)).astype(np.uint8) + 1
    return out


def worth_checking(one: np.ndarray, size: int, many: np.ndarray, sizes: np.ndarray, p: MinHashParams) -> tuple[np.ndarray, np.ndarray]:
    """Share of ranges in which signatures agree, and whether this and the sizes allow the similarity, of one signature with each of many."""
    agree = ((many == one) & (one > 0)).sum(axis=1)
    seen = np.maximum(((many > 0) | (one > 0)).sum(axis=1), 1)
    least = p.percent / 100
    union = (sizes + size) / (1 + least)
    spread = np.sqrt(least * (1 - least) / seen * np.clip(1 - seen / np.maximum(union, 1), 0, 1))
    near = agree / seen
    return near, near >= least - p.deviations * spread - 0.01


def coarser(fine: np.ndarray) -> np.ndarray:
    """The signature of ranges four times as wide."""
    quarters = fine.reshape(*fine.shape[:-1], -1, 4)
    out = quarters[..., 0].copy()
    for k in range(1, 4):
        np.copyto(out, quarters[..., k], where=out == 0)
    return out


def fitting(one: int, many: np.ndarray, fine: np.ndarray, coarse: np.ndarray, sizes: np.ndarray, p: MinHashParams) -> tuple[np.ndarray, np.ndarray]:
    """Those of many worth an exact check with one, all places in the arrays, and how alike they look."""
    many = many[np.minimum(sizes[many], sizes[one]) * 100 >= np.maximum(sizes[many], sizes[one]) * p.percent]
    for level in (coarse, fine):
        if not len(many):
            break
        near, fits = worth_checking(level[one], sizes[one], level[many], sizes[many], p)
        near, many = near[fits], many[fits]
    return (near, many) if len(many) else (np.empty(0), many)


def _texts(docs: DataFrame, members: DataFrame, chosen: DataFrame, p: MinHashParams) -> DataFrame:
    """(id, text) of the members' documents; few ids are broadcast, more are shuffled with the texts. Of an id in chosen(id, low, high) the text of that set."""
    ids = members.select("id").distinct()
    few = ids.limit(p.most_broadcast_ids + 1).count() <= p.most_broadcast_ids
    found = docs.join(F.broadcast(ids) if few else ids, "id", "left_semi")
    if not chosen.isEmpty():

        def of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in slices(batches):
                wanted = list(zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True))
                keep = [w[0] is None or digest(next(shingle_sets([t.as_py()], p.width))) == w for w, t in zip(wanted, batch.column(1).cast(pa.binary()), strict=True)]
                yield batch.select([0, 1]).filter(pa.array(keep, pa.bool_()))

        found = found.where("text is not null").join(chosen, "id", "left").select("id", "text", "low", "high").mapInArrow(of, "id long, text string")
    return found.dropDuplicates(["id"])


def _fine(texts: DataFrame, reps: DataFrame, p: MinHashParams) -> DataFrame:
    """(id, size, fine, sig) of texts(id, text)."""

    def of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            sets = list(shingle_sets(batch.column(1).cast(pa.binary()).to_pylist(), p.width))
            fine = [fine_signature(x, p.fine_bits).tobytes() for x in sets]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([len(x) for x in sets], pa.int64()), pa.array(fine, pa.binary())], names=["id", "size", "fine"])

    return texts.mapInArrow(of, "id long, size long, fine binary").join(reps.select("id", "sig"), "id")


def _alike(pairs: DataFrame, fine: DataFrame, p: MinHashParams) -> DataFrame:
    """The pairs whose sizes and fine signatures allow the similarity."""
    sides = [fine.select(F.col("id").alias(k), F.col("size").alias(f"n{k}"), F.col("fine").alias(f"f{k}")) for k in "ab"]
    both = pairs.join(sides[1], "b").join(sides[0], "a")

    def of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            sizes = np.stack([batch.column(k).to_numpy() for k in (2, 3)], axis=1)
            keep = []
            for row, (x, y) in enumerate(zip(batch.column(4), batch.column(5), strict=True)):
                two = np.frombuffer(x.as_py() + y.as_py(), np.uint8).reshape(2, -1)
                keep.append(bool(len(fitting(0, np.array([1]), two, coarser(two), sizes[row], p)[1])))
            yield pa.RecordBatch.from_arrays(list(batch.columns[:2]), names=["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return both.select("a", "b", "na", "nb", "fa", "fb").mapInArrow(of, "a long, b long")


def _verified(pairs: DataFrame, texts: DataFrame, p: MinHashParams) -> DataFrame:
    """(a, b, linked): each pair held against the whole texts' full sets."""
    both = pairs.join(texts.select(F.col("id").alias("b"), F.col("text").alias("tb")), "b").join(
        texts.select(F.col("id").alias("a"), F.col("text").alias("ta")), "a"
    )

    def of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: OrderedDict[int, np.ndarray] = OrderedDict()

        def set_of(key: int, column: pa.Array, row: int) -> np.ndarray:
            if key in kept:
                kept.move_to_end(key)
                return kept[key]
            found = next(shingle_sets([column[row].as_py()], p.width))
            kept[key] = found
            if len(kept) > 256:
                kept.popitem(last=False)
            return found

        for batch in slices(batches):
            keys = [batch.column(k).to_pylist() for k in (0, 1)]
            texts = [batch.column(k).cast(pa.binary()) for k in (2, 3)]
            linked = []
            for row, (x, y) in enumerate(zip(*keys, strict=True)):
                one, two = set_of(x, texts[0], row), set_of(y, texts[1], row)
                common = overlap(one, two)
                linked.append(100 * common >= p.percent * (len(one) + len(two) - common))
            yield pa.RecordBatch.from_arrays([*batch.columns[:2], pa.array(linked, pa.bool_())], names=["a", "b", "linked"])

    return both.select("a", "b", "ta", "tb").mapInArrow(of, "a long, b long, linked boolean")


def _mixed(members: DataFrame, labels: DataFrame) -> DataFrame:
    """(bucket, band, id, component, main, n, top) of buckets that still hold several components: main is the commonest, top its size, n the
    bucket's. Of buckets with the same members the first band's stays; one of two members has been tested."""
    now = members.select("bucket", "band", "id").join(labels, "id", "left").select("bucket", "band", "id", F.coalesce("component", "id").alias("component"))
    by_part = now.groupBy("bucket", "band", "component").agg(F.count(F.lit(1)).alias("n"), F.bit_xor(F.xxhash64("id")).alias("mark"))
    several = (
        by_part.groupBy("bucket", "band")
        .agg(F.max_by("component", F.struct("n", "component")).alias("main"), F.sum("n").alias("n"), F.max("n").alias("top"), F.count(F.lit(1)).alias("parts"), F.bit_xor("mark").alias("mark"))
        .where("parts > 1 and n > 2")
        .groupBy("n", "mark")
        .agg(F.min(F.struct("band", "bucket", "main", "n", "top")).alias("one"))
        .select("one.bucket", "one.main", "one.n", "one.top")
    )
    return now.join(several, "bucket")


def _unsettled(mixed: DataFrame, failed: DataFrame, fine: DataFrame, p: MinHashParams) -> DataFrame:
    """Untested pairs (a, b) across components within the same bucket whose fine signatures allow the similarity; b was held against a's block.

    Members outside the bucket's commonest component are held against all its members, block by block. Of pairs that are surely
    alike a block returns a forest over what is still apart, of others a member's most alike; later rounds take what is left.
    """
    blocks = lambda n: F.ceil(n / F.lit(float(p.block))).cast("int")
    tried = failed.groupBy(F.col("b").alias("id")).agg(F.collect_set("a").alias("tried"))
    rows = mixed.join(fine, "id").join(tried, "id", "left")
    rows = rows.select("bucket", "band", "id", "component", "size", "fine", "sig", "tried", (F.col("component") != F.col("main")).alias("apart"), blocks(F.col("n")).alias("wide"), blocks(F.col("n") - F.col("top")).alias("tall"))
    place = F.xxhash64("id")
    # A bucket of one block is one group of rows, in which those apart are held against all; else each of its rows goes to a row, or a column, of blocks.
    small = rows.where("wide = 1").withColumns({"row": F.lit(0), "col": F.lit(0), "probe": F.col("apart"), "whole": F.lit(True)})
    large = rows.where("wide > 1")
    whole = large.withColumns({"row": F.explode(F.sequence(F.lit(0), F.col("tall") - 1)), "col": F.pmod(place, "wide").cast("int"), "probe": F.lit(False), "whole": F.lit(True)})
    probes = large.where("apart").withColumns({"col": F.explode(F.sequence(F.lit(0), F.col("wide") - 1)), "row": F.pmod(place, "tall").cast("int"), "probe": F.lit(True), "whole": F.lit(False)})
    least, most = p.percent / 100 + 0.05, p.partners
    columns = ["bucket", "row", "col", "band", "id", "component", "size", "fine", "sig", "tried", "probe", "whole"]

    def of(table: pa.Table) -> pa.Table:
        probe, inside = (np.asarray(table.column(c).to_pylist(), bool) for c in ("probe", "whole"))
        ids, parts, sizes = (np.asarray(table.column(c).to_pylist(), np.int64) for c in ("id", "component", "size"))
        fine = np.frombuffer(b"".join(table.column("fine").to_pylist()), np.uint8).reshape(len(ids), -1)
        coarse, bands = coarser(fine), np.frombuffer(b"".join(table.column("sig").to_pylist()), "<u8").reshape(len(ids), -1)
        tried, band = table.column("tried").to_pylist(), table.column("band")[0].as_py()
        at, order = np.flatnonzero(inside), np.argsort(ids, kind="stable")
        # Tested pairs of this group as place x rows + place, from either side.
        owner = np.repeat(np.arange(len(ids)), [len(t) if t else 0 for t in tried])
        other = np.fromiter((x for t in tried if t for x in t), np.int64, len(owner))
        left, right = np.searchsorted(ids[order], other, "left"), np.searchsorted(ids[order], other, "right")
        pick = np.repeat(left, right - left) + np.arange((right - left).sum()) - np.repeat(np.cumsum(right - left) - (right - left), right - left)
        one, two = np.repeat(owner, right - left), order[pick]
        known = np.unique(np.concatenate([one * len(ids) + two, two * len(ids) + one]))
        found: list[tuple[float, int, int, int, int]] = []
        unsure: list[tuple[int, int]] = []
        for i in np.flatnonzero(probe):
            fit = at[parts[at] != parts[i]]
            fit = fit[~(bands[fit, :band] == bands[i, :band]).any(axis=1)]
            if len(known) and len(fit):
                codes = i * len(ids) + fit
                spot = np.minimum(np.searchsorted(known, codes), len(known) - 1)
                fit = fit[known[spot] != codes]
            near, fit = fitting(i, fit, fine, coarse, sizes, p)
            sure = near >= least
            found += [(-float(n), int(ids[i]), int(ids[j]), int(parts[i]), int(parts[j])) for n, j in zip(near[sure], fit[sure], strict=True)]
            near, fit = near[~sure], fit[~sure]
            unsure += [(int(ids[i]), int(ids[j])) for j in fit[np.lexsort((ids[fit], -near))][:most]]
            if len(found) > 1 << 17:
                found = forest(found)
        pairs = sorted({(y, x) for x, y in [*unsure, *(f[1:3] for f in forest(found))]})
        return pa.table({"a": pa.array([x for x, _ in pairs], pa.int64()), "b": pa.array([y for _, y in pairs], pa.int64())})

    found = small.select(columns).unionByName(whole.select(columns)).unionByName(probes.select(columns)).groupBy("bucket", "row", "col").applyInArrow(of, "a long, b long")
    low, high = F.least("a", "b").alias("low"), F.greatest("a", "b").alias("high")
    return found.groupBy(low, high).agg(F.max("b").alias("b")).select(F.when(F.col("b") == F.col("low"), F.col("high")).otherwise(F.col("low")).alias("a"), "b")


def forest(pairs: list[tuple[float, int, int, int, int]]) -> list[tuple[float, int, int, int, int]]:
    """Of (rank, a, b, component of a, component of b) those that, taken in order, join components that are still apart."""
    root: dict[int, int] = {}

    def top(x: int) -> int:
        while root.get(x, x) != x:
            root[x] = root.get(root[x], root[x])
            x = root[x]
        return x

    kept = []
    for pair in sorted(pairs):
        x, y = top(pair[3]), top(pair[4])
        if x != y:
            root[max(x, y)] = min(x, y)
            kept.append(pair)
    return kept


def near_duplicates(docs: DataFrame, params: MinHashParams | None = None, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """One row a document: id, n_shingles, component_id (least id reachable over links) and kept (it is its own component's id).

    Null and empty texts, or texts of white space alone, have no shingles and stay alone. Rows that repeat an id are one document: with
    texts of several sets it is the one of most shingles (then of the greatest digest) that is linked, and all its rows with shingles get that component,
    each with its own n_shingles. Rows without an id are never linked, have no component and are kept. Other columns are ignored.
    An empty table gives an empty result.
    """
    p = params or MinHashParams()
    docs = only(docs, [id_column, text_column]).toDF("id", "text").withColumn("id", F.col("id").cast("long"))
    features = scratch(_features(docs, p), "features")
    with_set = features.where("id is not null and n_shingles > 0")
    own = F.struct("n_shingles", "low", "high")
    chosen = scratch(with_set.groupBy("id").agg(F.min(own).alias("least"), F.max(own).alias("most")).where("least <> most").select("id", "most.low", "most.high"), "chosen")
    others = with_set.join(chosen.select(F.col("id").alias("of"), F.struct("low", "high").alias("linked")), F.col("id") == F.col("of"), "left").drop("of")
    reps = scratch(
        others.where(F.col("linked").isNull() | (F.struct("low", "high") == F.col("linked"))).groupBy("low", "high").agg(F.min("id").alias("id"), F.first("n_shingles").alias("n"), F.max("sig").alias("sig")), "classes"
    )
    bands = F.transform(F.sequence(F.lit(0), F.lit(p.bands - 1)), lambda k: F.xxhash64(k, F.col("sig").substr(k * 8 + 1, F.lit(8))))
    buckets = reps.select("id", F.posexplode(bands).alias("band", "bucket"))
    centres = buckets.groupBy("bucket").agg(F.min("id").alias("centre"), F.max("id").alias("last")).where("centre < last").select("bucket", "centre")
    members = scratch(buckets.join(centres, "bucket"), "members")
    pairs = members.where("id <> centre").select(F.col("centre").alias("a"), F.col("id").alias("b")).distinct()
    texts = scratch(_texts(docs, members, chosen, p), "texts")
    fine = scratch(_fine(texts, reps, p), "fine")
    tested = scratch(_verified(scratch(_alike(pairs, fine, p), "pairs"), texts, p), "tested")
    links = scratch(connected_components(tested.where("linked")), "labels")
    while True:
        mixed = scratch(_mixed(members, links), "mixed")
        more = scratch(_unsettled(mixed, tested.where("not linked"), fine, p), "pairs")
        if more.isEmpty():
            break
        new = scratch(_verified(more, texts, p), "tested")
        members, tested = mixed, tested.unionByName(new)
        if not new.where("linked").isEmpty():
            links = scratch(connected_components(tested.where("linked")), "labels")
    classes = reps.select("low", "high", F.col("id").alias("rep")).join(links.withColumnRenamed("id", "rep"), "rep", "left").select("low", "high", F.coalesce("component", "rep").alias("part"))
    alone = features.where("id is null or n_shingles = 0").select("id", "n_shingles", F.col("id").alias("component_id"))
    linked = F.coalesce("linked", F.struct("low", "high"))
    grouped = others.withColumns({"low": linked["low"], "high": linked["high"]}).join(classes, ["low", "high"]).select("id", "n_shingles", F.col("part").alias("component_id"))
    return alone.unionByName(grouped).select(
        F.col("id").alias(id_column), "n_shingles", "component_id", F.coalesce(F.col("id") == F.col("component_id"), F.lit(True)).alias("kept")
    )
