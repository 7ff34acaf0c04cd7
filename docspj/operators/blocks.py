"""Distances of blocks of vectors from blocks of probes, by matrix products.

A row of a packed table is a block: an Arrow stream of up to BLOCK rows. Blocks meet by a cross join, so neither side goes to the driver, and
any number of probes can be asked. A product only rules pairs out; the distance of what it leaves is summed place by place, as a Column would.
"""

from __future__ import annotations

import decimal
import math
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BLOCK = 2048
#: Rows of a block that a product takes at once, and pairs whose distances are summed at once.
_ROWS, _PAIRS = 2048, 1 << 16
#: Vectors whose squared length is more are not screened in single precision.
_LONGEST = 1e12
#: More rows than these are not broadcast; blocks then meet in a Cartesian product.
MOST_BROADCAST = 100_000
#: (rows, columns, whether a pair may be taken) of the parts of two blocks that a search compares.
Parts = Callable[[pd.DataFrame, np.ndarray, pd.DataFrame, np.ndarray], Iterator[tuple[np.ndarray, np.ndarray, np.ndarray | None]]]


def packed(df: DataFrame) -> DataFrame:
    """(block_no, block): df's rows in blocks, as they lie."""

    def of(batches):
        at = TaskContext.get().partitionId() << 32
        for batch in batches:
            for low in range(0, batch.num_rows, BLOCK):
                sink, part = pa.BufferOutputStream(), batch.slice(low, BLOCK)
                with pa.ipc.new_stream(sink, part.schema) as stream:
                    stream.write_batch(part)
                yield pa.RecordBatch.from_arrays([pa.array([at], pa.int64()), pa.array([sink.getvalue().to_pybytes()], pa.binary())], ["block_no", "block"])
                at += 1

    return df.mapInArrow(of, "block_no long, block binary")


def unpacked(block: bytes) -> tuple[pd.DataFrame, np.ndarray]:
    """A block's rows, and their vectors `vec` as a matrix; a null vector is not a number."""
    table = pa.ipc.open_stream(block).read_all()
    vectors, rest = table["vec"].combine_chunks(), table.drop_columns(["vec"]).to_pandas()
    none = vectors.is_null().to_numpy(zero_copy_only=False)
    flat = vectors.drop_null().flatten().to_numpy(zero_copy_only=False).astype(float)
    matrix = np.full((len(none), len(flat) // max(1, int((~none).sum()))), np.nan)
    matrix[~none] = flat.reshape(int((~none).sum()), -1)
    return rest, matrix


def meeting(vectors: DataFrame, probes: DataFrame) -> DataFrame:
    """Every block of vectors(key, vec, ...) beside every block of probes(probe, vec, ...)."""
    n = probes.count()
    asked = packed(probes.repartition(max(1, math.ceil(n / BLOCK)))).select(F.col("block_no").alias("probe_no"), F.col("block").alias("probes"))
    return packed(vectors).crossJoin(F.broadcast(asked) if n <= MOST_BROADCAST else asked.coalesce(max(1, n // 65536)))


def squares(v: np.ndarray, p: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Squared distances by a matrix product, and for each column how far they may be off, 1e-9 of a distance's rounding included."""
    own, other = (v * v).sum(1), (p * p).sum(1)
    found = np.maximum(own[:, None] + other[None] - 2 * (v @ p.T), 0)
    found[np.isnan(found)] = np.inf
    top = np.nanmax(own) if len(own) and not np.isnan(own).all() else 0.0
    return found, 1e-8 * (1 + np.nan_to_num(other) + top)


class Screen:
    """A block's vectors in single precision, each with its squared length at hand, so that one product gives squared distances."""

    def __init__(self, v: np.ndarray):
        self.v, self.lengths = v, (v * v).sum(1)
        self.none = np.isnan(self.lengths)
        own = np.where(self.none, 0.0, self.lengths)
        self.top = float(own.max()) if len(own) else 0.0
        self.single, self._hashes = self.top <= _LONGEST, None
        if self.single:
            held = np.where(self.none[:, None], 0.0, v)
            one = np.ones((len(v), 1))
            self.left = np.concatenate([held, own[:, None], one], 1).astype(np.float32)
            self.right = np.concatenate([-2 * held, one, own[:, None]], 1).astype(np.float32).T

    def hashes(self, rows: pd.DataFrame) -> np.ndarray:
        """The rows' hashes as a matrix, made once."""
        if self._hashes is None:
            self._hashes = np.array(rows["hashes"].tolist())
        return self._hashes


def screened(rows: Screen, columns: Screen, own: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """squares of some rows and columns of two blocks, in single precision; how far they may be off bounds its rounding in any order of summing."""
    if not (rows.single and columns.single):
        return squares(rows.v[own], columns.v[at])
    left = rows.left if len(own) == len(rows.left) else rows.left[own]
    found = left @ (columns.right if len(at) == columns.right.shape[1] else columns.right[:, at])
    if rows.none.any():
        found[rows.none[own]] = np.inf
    if columns.none.any():
        found[:, columns.none[at]] = np.inf
    off = (rows.left.shape[1] + 8) * 2.5e-7 * (np.nan_to_num(columns.lengths[at]) + rows.top) + 1e-8
    return found, off.astype(np.float32)


def distances(v: np.ndarray, p: np.ndarray, rows: np.ndarray, columns: np.ndarray) -> np.ndarray:
    """Of each pair, the root of the squares' sum in the order of the places."""
    found = np.empty(len(rows))
    for low in range(0, len(rows), _PAIRS):
        a, b = v[rows[low : low + _PAIRS]], p[columns[low : low + _PAIRS]]
        total = np.zeros(len(a))
        for j in range(v.shape[1]):
            off = a[:, j] - b[:, j]
            total += off * off
        found[low : low + _PAIRS] = np.sqrt(total)
    return found


def nearest(df: DataFrame, column: str, centres: np.ndarray, n: int, name: str) -> DataFrame:
    """df with the numbers of the n centres nearest to its vectors, in order, ties by number; distances are summed as in a Column. A null vector's come by number."""
    at, many = df.columns.index(column), np.asarray(centres, float)

    def of(batches):
        for whole in batches:
            for low in range(0, whole.num_rows, BLOCK):
                batch = whole.slice(low, BLOCK)
                vecs = batch.column(at)
                none = vecs.is_null().to_numpy(zero_copy_only=False)
                flat = vecs.drop_null().flatten().to_numpy(zero_copy_only=False).astype(float)
                found = np.full((len(none), len(many)), np.nan)
                if len(flat):
                    v = np.ascontiguousarray(flat.reshape(-1, many.shape[1]).T)
                    for i, c in enumerate(many):
                        total = np.zeros(v.shape[1])
                        for j in range(len(v)):
                            off = v[j] - c[j]
                            total += off * off
                        found[~none, i] = np.sqrt(total)
                order = np.argsort(found, axis=1, kind="stable")[:, :n].astype(np.int32)
                lists = pa.ListArray.from_arrays(pa.array(np.arange(len(order) + 1, dtype=np.int32) * order.shape[1]), pa.array(order.ravel()))
                yield pa.RecordBatch.from_arrays([*batch.columns, lists], [*batch.schema.names, name])

    declared = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields)
    return df.mapInArrow(of, f"{declared}, `{name}` array<int>")


def rounded(x: np.ndarray) -> np.ndarray:
    """x rounded to 9 places, halves up, by its shortest decimal form: as `round` of a Column."""
    scaled = x * 1e9
    whole = np.floor(scaled + 0.5)
    unsure = np.flatnonzero(np.isfinite(x) & (np.abs(scaled - np.floor(scaled) - 0.5) < 1e-3))
    for i in unsure:
        whole[i] = float(decimal.Decimal(repr(float(x[i]))).scaleb(9).to_integral_value(decimal.ROUND_HALF_UP))
    return whole / 1e9


def everything(rows: pd.DataFrame, v: np.ndarray, asked: pd.DataFrame, p: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray | None]]:
    for low in range(0, len(rows), _ROWS):
        yield np.arange(low, min(low + _ROWS, len(rows))), np.arange(len(asked)), None


def _pairs(batches):
    """(rows and screen of a block, probes' block, its rows and screen) of each meeting; a block is unpacked once in a row."""
    opened = lambda block: (lambda rows, v: (rows, Screen(v)))(*unpacked(block))
    last, held = None, {}
    for batch in batches:
        for block, no, probes in zip(batch.column("block"), batch.column("probe_no"), batch.column("probes"), strict=True):
            data = block.as_buffer()
            if last is None or not data.equals(last[0]):
                last = (data, opened(block.as_py()))
            if no.as_py() not in held:
                held[no.as_py()] = opened(probes.as_py())
            yield last[1], no.as_py(), held[no.as_py()]


def topk(vectors: DataFrame, probes: DataFrame, k: int, parts: Parts = everything) -> DataFrame:
    """(probe, dist, key): of each task the k nearest vectors of each probe, distances rounded to 9 places, ties by key; null distances last."""

    def of(batches):
        kept: dict[int, pd.DataFrame] = {}
        bounds: dict[int, np.ndarray] = {}
        ids: dict[int, np.ndarray] = {}
        for (rows, left), no, (asked, right) in _pairs(batches):
            v, p = left.v, right.v
            ids[no] = asked["probe"].to_numpy()
            bound = bounds.setdefault(no, np.full(len(p), np.inf))
            pairs = []
            for own, columns, may in parts(rows, v, asked, p):
                if not len(own) or not len(columns):
                    continue
                found, off = screened(left, right, own, columns)
                if may is not None:
                    found[~may] = np.nan
                least = bound[columns]
                if np.isinf(least).any():
                    # No more than the k least of a part are taken, and what is as near as the last of them.
                    place = min(k, len(own)) - 1
                    least = np.minimum(np.partition(found, place, axis=0)[place] + off, least)
                    least[np.isnan(least)] = np.inf
                i, j = np.nonzero(found <= (least + 2 * off).astype(found.dtype))
                pairs.append((own[i], columns[j]))
            if not sum(len(i) for i, _ in pairs):
                continue
            # The parts of a block are ranked together.
            i, at = (np.concatenate(x) for x in zip(*pairs, strict=True))
            dist = rounded(distances(v, p, i, at))
            new = pd.DataFrame({"at": at, "dist": dist, "key": rows["key"].to_numpy()[i]})
            rest = None
            if no in kept:
                # Only probes that are met now are ranked again.
                met = np.zeros(len(p), bool)
                met[at] = True
                again = met[kept[no]["at"].to_numpy()]
                rest, new = kept[no][~again], pd.concat([kept[no][again], new])
            both = new.sort_values(["at", "dist", "key"]).groupby("at", sort=False).head(k)
            kept[no] = both if rest is None else pd.concat([rest, both])
            full = both.groupby("at")["dist"].agg(["size", "max"])
            full = full[full["size"] == k]
            last = full["max"].to_numpy()
            # A rounded distance may lie below the vector's own by half of its last place.
            bound[full.index.to_numpy()] = np.where(np.isnan(last), np.inf, (last + 1e-9) ** 2)
        for no, both in kept.items():
            dist = both["dist"].to_numpy()
            yield pa.RecordBatch.from_arrays([pa.array(ids[no][both["at"].to_numpy()], types[0]), pa.array(dist, mask=np.isnan(dist)), pa.array(both["key"], types[1])], ["probe", "dist", "key"])

    from pyspark.sql.pandas.types import to_arrow_type

    kinds = probes.schema["probe"].dataType, vectors.schema["key"].dataType
    types = tuple(to_arrow_type(t) for t in kinds)
    return meeting(vectors, probes).mapInArrow(of, f"probe {kinds[0].simpleString()}, dist double, key {kinds[1].simpleString()}")


def within(vectors: DataFrame, probes: DataFrame, radius: float) -> DataFrame:
    """(probe, key, dist) of all pairs within the radius."""

    def of(batches):
        for (rows, left), _, (asked, right) in _pairs(batches):
            v, p = left.v, right.v
            for own, columns, _may in everything(rows, v, asked, p):
                found, off = screened(left, right, own, columns)
                i, j = np.nonzero(found <= (radius * radius + off).astype(found.dtype))
                dist = distances(v, p, own[i], columns[j])
                near = dist <= radius
                if near.any():
                    yield pa.RecordBatch.from_arrays([pa.array(asked["probe"].to_numpy()[j[near]], types[0]), pa.array(rows["key"].to_numpy()[own[i[near]]], types[1]), pa.array(dist[near])], ["probe", "key", "dist"])

    from pyspark.sql.pandas.types import to_arrow_type

    kinds = probes.schema["probe"].dataType, vectors.schema["key"].dataType
    types = tuple(to_arrow_type(t) for t in kinds)
    return meeting(vectors, probes).mapInArrow(of, f"probe {kinds[0].simpleString()}, key {kinds[1].simpleString()}, dist double")


def joined(blocks: DataFrame, radius: float, n: int, key_type: str) -> DataFrame:
    """(a, b, dist), a < b, of packed(key, vec, hashes), durably written: pairs within the radius that share a hash at some place."""
    other = blocks.select(F.col("block_no").alias("probe_no"), F.col("block").alias("probes"))
    other = F.broadcast(other) if n <= MOST_BROADCAST else other.coalesce(max(1, n // 65536))
    both = blocks.crossJoin(other).where("block_no <= probe_no")

    def of(batches):
        for (rows, near), _, (asked, far) in _pairs(batches):
            v, p = near.v, far.v
            left, right = near.hashes(rows), far.hashes(asked)
            if not any(np.isin(left[:, j], right[:, j]).any() for j in range(left.shape[1])):
                continue
            a, b = rows["key"].to_numpy(), asked["key"].to_numpy()
            same = len(a) == len(b) and (a == b).all()
            for own, columns, _may in everything(rows, v, asked, p):
                found, off = screened(near, far, own, columns)
                i, j = np.nonzero(found <= (radius * radius + off).astype(found.dtype))
                i = own[i]
                fit = (left[i] == right[j]).any(1) & (a[i] < b[j] if same else a[i] != b[j])
                i, j = i[fit], columns[j[fit]]
                dist = distances(v, p, i, j)
                hit = dist < radius
                if hit.any():
                    x, y = a[i[hit]], b[j[hit]]
                    yield pa.RecordBatch.from_arrays([pa.array(np.minimum(x, y)), pa.array(np.maximum(x, y)), pa.array(dist[hit])], ["a", "b", "dist"])

    return both.mapInArrow(of, f"a {key_type}, b {key_type}, dist double")
