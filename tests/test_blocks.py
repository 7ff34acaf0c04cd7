"""Vector search in blocks, against plain loops."""

import math
import random

import pytest
from pyspark.sql import functions as F

from docspj.operators import blocks
from docspj.operators.index import ExactIndex, IVFIndex, LSHIndex, PQIndex


def vectors(n=300, width=8, seed=4):
    rng = random.Random(seed)
    found = [[rng.gauss(0, 1) for _ in range(width)] for _ in range(n)]
    for i in range(0, n, 3):  # a third are copies of one another, in tens
        found[i] = found[i - i % 30]
    return found


@pytest.fixture(scope="module")
def table(spark):
    rows = [(i, v) for i, v in enumerate(vectors())]
    return spark.createDataFrame([*rows, (1000, None)], "vec_id long, embedding array<double>").repartition(5)


@pytest.fixture(scope="module")
def probes(table):
    return table.where("vec_id % 20 = 0 and embedding is not null").select(F.col("vec_id").alias("probe"), F.col("embedding").alias("pvec"))


def test_topk_ties_and_nulls(table, probes, monkeypatch):
    """Copies tie by key, a vector that is null comes last (it came first), and more probes than may be broadcast are answered (they were refused)."""
    v = vectors()
    order = lambda p: [i for _, i in sorted((round(math.dist(v[p], x), 9), i) for i, x in enumerate(v))]
    want = {(p, r + 1, i) for p in range(0, 300, 20) for r, i in enumerate([*order(p), 1000][-3:], 298)} | {(p, r + 1, i) for p in range(0, 300, 20) for r, i in enumerate(order(p)[:5])}
    for most in (100_000, 3):
        monkeypatch.setattr(blocks, "MOST_BROADCAST", most)
        got = {(r.probe, r.rank, r.key) for r in ExactIndex(table).topk(probes, 301).where("rank <= 5 or rank > 298").collect()}
        assert got == want
        assert {(r.probe, r.rank, r.key) for r in ExactIndex(table).topk(probes, 5).collect()} == {x for x in want if x[1] <= 5}


def test_rounding_as_a_column(spark):
    values = [1.0000000005, 0.9999999995, 1.2345678915, 0.1234567885, 1.1234567895, 2.5e-10, 5e-10, 7e-10, 1.4142135623730951]
    rows = spark.createDataFrame([(x,) for x in values], "x double").select("x", F.round("x", 9).alias("y")).collect()
    import numpy as np

    assert list(blocks.rounded(np.array([r.x for r in rows]))) == [r.y for r in rows]


def test_ivf_of_all_cells_is_exact(table, probes):
    own = table.where("embedding is not null")
    exact = {(r.probe, r.rank, r.key, r.dist) for r in ExactIndex(own).topk(probes, 5).collect()}
    index = IVFIndex(own, 4)
    assert {(r.probe, r.rank, r.key, r.dist) for r in index.topk(probes, 5, 4).collect()} == exact
    cell, v = {r.key: r.cell for r in index.vectors.collect()}, vectors()
    for p in {r.probe for r in probes.collect()}:
        near = min(range(4), key=lambda c: math.dist(v[p], index.centres[c]))
        want = [i for _, i in sorted((round(math.dist(v[p], x), 9), i) for i, x in enumerate(v) if cell[i] == near)][:5]
        assert [r.key for r in index.topk(probes.where(F.col("probe") == p), 5, 1).orderBy("rank").collect()] == want


def test_pq_shortlist_by_code(table, probes):
    """A shortlist of all ranks exactly; a shorter one holds the nearest by code, ranked by their distances."""
    own, v = table.where("embedding is not null"), vectors()
    exact = {(r.probe, r.rank, r.key) for r in ExactIndex(own).topk(probes, 5).collect()}
    index = PQIndex(own, 4, 4)
    assert {(r.probe, r.rank, r.key) for r in index.topk(probes, 5, 300).collect()} == exact
    stand = {r.key: [x for j, c in enumerate(r.code) for x in index.books[j][c]] for r in index.codes.collect()}
    got = {}
    for r in index.topk(probes, 5, 60).collect():
        got.setdefault(r.probe, []).append((r.rank, r.key))
    for p, hits in got.items():
        reach = sorted(math.dist(v[p], x) for x in stand.values())[59] + 1e-7
        listed = [i for i, x in stand.items() if math.dist(v[p], x) <= reach]
        assert [k for _, k in sorted(hits)] == [i for _, i in sorted((round(math.dist(v[p], v[i]), 9), i) for i in listed)][:5]


def test_range(table, probes):
    v = vectors()
    got = {(r.probe, r.key): r.dist for r in ExactIndex(table).range(probes, 2.5).collect()}
    want = {(p, i): math.dist(v[p], x) for p in range(0, 300, 20) for i, x in enumerate(v) if math.dist(v[p], x) <= 2.5}
    assert got.keys() == want.keys() and all(abs(got[x] - want[x]) < 1e-12 for x in want)


def test_lsh_join_by_buckets(spark, table, monkeypatch):
    """Pairs nearer than the radius that share a bucket, each once, copies among them, whichever way blocks meet."""
    own, v = table.where("embedding is not null"), vectors()
    for most in (100_000, 3):
        monkeypatch.setattr(blocks, "MOST_BROADCAST", most)
        monkeypatch.setattr(blocks, "BLOCK", 40)
        index = LSHIndex(own, 0.5, 3)
        buckets = {r.key: [h[0] for h in r.hashes] for r in index.model.transform(index.vectors).collect()}
        want = {(a, b) for a in range(300) for b in range(a + 1, 300) if math.dist(v[a], v[b]) < 1.5 and any(x == y for x, y in zip(buckets[a], buckets[b], strict=True))}
        got = [(r.a, r.b) for r in index.join(1.5).collect()]
        assert len(got) == len(set(got)) and set(got) == want


def test_screen_keeps_what_is_at_the_bound(spark):
    """In single precision no product is off by more than it says, so distances at the radius, and long vectors, are judged as by plain sums; and whole-number grids tie."""
    import numpy as np

    rng = np.random.default_rng(7)
    for scale in (1e-6, 1.0, 300.0, 1e9):
        v, p = rng.normal(size=(200, 64)) * scale, rng.normal(size=(50, 64)) * scale
        p[:40] = v[:40] + rng.normal(size=(40, 64)) * scale * 1e-5
        a, b = blocks.Screen(v), blocks.Screen(p)
        found, off = blocks.screened(a, b, np.arange(200), np.arange(50))
        true = ((v[:, None].astype(np.longdouble) - p[None]) ** 2).sum(2)
        assert a.single == (scale < 1e6) and (np.abs(found - true) <= off).all()
    grid = [(i, [float(i % 7), float(i % 5), float(i % 3), 0.0]) for i in range(420)]
    table = spark.createDataFrame(grid, "vec_id long, embedding array<double>").repartition(3)
    asked = table.where("vec_id % 20 = 0").select(F.col("vec_id").alias("probe"), F.col("embedding").alias("pvec"))
    want = {(q, i) for q, x in grid[::20] for i, y in grid if math.dist(x, y) <= math.sqrt(5)}
    assert {(r.probe, r.key) for r in ExactIndex(table).range(asked, math.sqrt(5)).collect()} == want
    near = {(q, i) for q, x in grid[::20] for i in sorted(range(420), key=lambda i: (round(math.dist(x, grid[i][1]), 9), i))[:9]}
    assert {(r.probe, r.key) for r in ExactIndex(table).topk(asked, 9).collect()} == near


def test_nearest_centres_as_columns(spark, table):
    """Cells by blocks are those that Columns give, ties and null vectors too."""
    from docspj.functions.text import euclid

    centres = [[0.5] * 8, [-0.5] * 8, [0.5] * 8, [1.0, -1.0] * 4]
    cells = F.array(*[F.struct(euclid(F.col("embedding"), F.lit(c)).alias("d"), F.lit(i).alias("cell")) for i, c in enumerate(centres)])
    want = table.select("vec_id", F.transform(F.slice(F.array_sort(cells), 1, 3), lambda c: c["cell"]).alias("cells"))
    got = blocks.nearest(table, "embedding", centres, 3, "cells").select("vec_id", "cells")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
