"""Two-level index over documents and segments, and vector search back ends."""

from __future__ import annotations

import json
import math
from collections.abc import Callable, Sequence
from dataclasses import dataclass, replace
from functools import reduce

import numpy as np
from pyspark.ml.clustering import KMeans
from pyspark.ml.feature import BucketedRandomProjectionLSH
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from docspj.functions.text import DIMENSIONS, distance_to, embed, euclid, l2n, norm2, python_embed, unit
from docspj.functions.udfs import callable_embedder
from docspj.operators import batches, blocks
from docspj.operators.segments import segment, summarise
from docspj.session import cut


def dense(vector: Column, squared: Column, d: int = DIMENSIONS) -> Column:
    """A vector's map as an array of doubles of length one; the empty vector is zeros."""
    scale = F.when(squared > 0, F.sqrt(squared.cast("double"))).otherwise(1.0)
    return F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda i: F.coalesce(F.try_element_at(vector, i), F.lit(0)).cast("double") / scale)


@dataclass
class Cells:
    """k-means cells of the segments' vectors: centres, and the largest distance of a member from its centre."""

    centres: list[list[float]]
    radii: list[float]

    def within(self, probes: Sequence[tuple[Sequence[float], float]]) -> list[int]:
        """Cells that may hold a vector within the radius of one of (point, radius): the triangle inequality rules the others out."""
        return [i for i, (c, r) in enumerate(zip(self.centres, self.radii, strict=True)) if any(math.dist(c, p) <= radius + r + 1e-9 for p, radius in probes)]


@dataclass
class Codes:
    """Product codes of the segments' vectors: for each of m parts, ks centres; each segment holds its codes and its distance from what they stand for."""

    books: list[list[list[float]]]

    def least_distance(self, code: Column, error: Column, point: Sequence[float]) -> Column:
        """A bound from below of a segment's distance from a point, by its codes alone."""
        width = len(self.books[0][0])
        table = F.array(*[F.array(*[F.lit(sum((x - y) ** 2 for x, y in zip(c, point[j * width : (j + 1) * width], strict=True))) for c in book]) for j, book in enumerate(self.books)])
        squares = F.aggregate(F.zip_with(table, code, lambda t, c: F.element_at(t, c + 1)), F.lit(0.0), lambda s, x: s + x)
        return F.sqrt(squares) - error


@dataclass
class TwoLevelIndex:
    """docs(corpus, doc_key, vecs, n2s) and segments(corpus, doc_key, seg_no, text, n_tokens, vec, n2), both by doc_key.

    model: what embeds lists of texts, where it is not the hashed words. cells, codes: of the segments, if made. parts(only, shown) makes
    (corpus, doc_key, parts, n_tokens), the segments' texts in order, an array a document, of all documents or of only(doc_key), where they are to be had so;
    and the whole document's tokens. With shown, a condition on a text, it may leave out segments for which that doesn't hold, such as many documents share.
    texts: the segments without vectors, where these are the hashed words of their texts and are made where they are asked for.
    """

    docs: DataFrame
    segments: DataFrame
    model: Callable[[list[str]], list[list[float]]] | None = None
    cells: Cells | None = None
    codes: Codes | None = None
    parts: Callable[..., DataFrame] | None = None
    texts: DataFrame | None = None

    @staticmethod
    def of_texts(docs: DataFrame, sim_threshold: float = 0.25, max_tokens: int = 200) -> TwoLevelIndex:
        """build, of opening sentences and hashed words, in one pass over the texts; written once, the segments without vectors."""
        rows = cut(batches.segmented(docs, sim_threshold, max_tokens, opening=True), "segments")
        texts = rows.where("seg_no is not null").drop("lead", "lead_n2")
        top = rows.where("lead_n2 is not null").select("corpus", "doc_key", F.array("lead").alias("vecs"), F.array("lead_n2").alias("n2s"))
        return TwoLevelIndex(top, batches.embedded(texts, "text"), texts=texts)

    @staticmethod
    def build(docs: DataFrame, summary: str = "lead", segments: DataFrame | None = None, d: int = DIMENSIONS, model: Callable[[list[str]], list[list[float]]] | None = None, **options) -> TwoLevelIndex:
        """Summaries and segments of docs(corpus, doc_key, text), embedded; a model embeds in batches, each text once."""
        one = summarise(docs, summary)
        texts = F.col("sentences") if summary == "multi" else F.array("summary")
        if model is None and segments is None and options.get("mode", "previous") == "previous" and not set(options) - {"mode", "sim_threshold", "max_tokens"}:
            below = batches.segmented(docs, d=d, **{k: v for k, v in options.items() if k != "mode"})
        else:
            below = segment(docs, d=d, **options) if segments is None else segments
            below = below if model is not None else batches.embedded(below, "text", d)
        if model is not None:
            place = lambda v: F.map_from_arrays(F.sequence(F.lit(0), F.size(v) - 1), l2n(v.cast("array<double>")))
            square = lambda v: F.aggregate(F.map_values(v), F.lit(0.0), lambda s, x: s + x * x)
            column = callable_embedder(model)
            rows = one.select("corpus", "doc_key", F.posexplode_outer(texts).alias("at", "text")).withColumn("made", column(F.col("text"))).withColumn("vec", place(F.col("made")))
            parts = F.transform(F.array_sort(F.collect_list(F.struct("at", F.map_entries("vec").alias("entries")))), lambda x: F.map_from_entries(x["entries"]))
            top = rows.groupBy("corpus", "doc_key").agg(parts.alias("vecs")).withColumn("n2s", F.transform("vecs", square))
            return TwoLevelIndex(top, below.withColumn("made", column(F.col("text"))).withColumn("vec", place(F.col("made"))).drop("made").withColumn("n2", square(F.col("vec"))), model)
        if summary == "multi":
            top = one.select("corpus", "doc_key", F.transform(texts, lambda t: embed(t, d)).alias("vecs")).withColumn("n2s", F.transform("vecs", norm2))
        elif summary == "lead":
            top = batches.led(docs, d)
        else:
            top = batches.embedded(one.select("corpus", "doc_key", "summary"), "summary", d).select("corpus", "doc_key", F.array("vec").alias("vecs"), F.array("n2").alias("n2s"))
        return TwoLevelIndex(top, below)

    def vector(self, text: str) -> list[float]:
        """A short text's vector on the driver, of length one."""
        if self.model is None:
            return unit(python_embed(text))
        found = [float(x) for x in self.model([text])[0]]
        length = math.sqrt(sum(x * x for x in found)) or 1.0
        return [x / length for x in found]

    @property
    def dimensions(self) -> int:
        return len(self.vector("dimensions"))

    def with_cells(self, cells: int = 16, sample: int = 20_000, seed: int = 1) -> TwoLevelIndex:
        """The segments with `cell`, by k-means on a bounded sample of least hashes; every segment is placed, and the radii are of all of them."""
        points = self._sampled(sample)
        centres = [c.tolist() for c in KMeans(k=cells, seed=seed, maxIter=15).fit(points.select(array_to_vector("point").alias("features"))).clusterCenters()]
        near = F.array_min(F.array(*[F.struct(distance_to(F.col("vec"), F.col("n2"), c).alias("d"), F.lit(i).alias("cell")) for i, c in enumerate(centres)]))
        placed = cut(self.segments.withColumn("near", near).withColumns({"cell": F.col("near.cell"), "cell_dist": F.col("near.d")}).drop("near"), "cells")
        radii = {r.cell: r.r for r in placed.groupBy("cell").agg(F.max("cell_dist").alias("r")).collect()}
        return replace(self, segments=placed.drop("cell_dist"), texts=None, cells=Cells(centres, [radii.get(i, -math.inf) for i in range(len(centres))]))

    def with_codes(self, m: int = 8, ks: int = 16, sample: int = 20_000, seed: int = 1) -> TwoLevelIndex:
        """The segments with `code` and `code_error`, books by k-means on a bounded sample; every segment is coded."""
        points, width, books = self._sampled(sample), self.dimensions // m, []
        for j in range(m):
            part = points.select(array_to_vector(F.slice("point", j * width + 1, width)).alias("features"))
            books.append([c.tolist() for c in KMeans(k=ks, seed=seed, maxIter=15).fit(part).clusterCenters()])
        square = lambda x, c: F.aggregate(F.zip_with(x, F.lit(c), lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, v: s + v)
        part = lambda j: F.slice("point", j * width + 1, width)
        best = F.array(*[F.array_min(F.array(*[F.struct(square(part(j), c).alias("d"), F.lit(i).alias("c")) for i, c in enumerate(book)])) for j, book in enumerate(books)])
        coded = self.segments.withColumn("point", dense(F.col("vec"), F.col("n2"), self.dimensions)).withColumn("best", best)
        coded = coded.withColumns({"code": F.transform("best", lambda b: b["c"]), "code_error": F.sqrt(F.aggregate("best", F.lit(0.0), lambda s, b: s + b["d"])) + 1e-9})
        return replace(self, segments=cut(coded.drop("point", "best"), "codes"), texts=None, codes=Codes(books))

    def _sampled(self, rows: int) -> DataFrame:
        few = self.segments.orderBy(F.xxhash64("doc_key", "seg_no"), "doc_key", "seg_no").limit(rows)
        return cut(few.select(dense(F.col("vec"), F.col("n2"), self.dimensions).alias("point")), "points")

    def reached(self, probes: Sequence[tuple[Sequence[float], float]], search: str = "scan") -> DataFrame:
        """Segments among which all lie that are within the radius of one of (point, radius). scan: all. cells, codes: those that a bound from below
        does not rule out, so nothing within is lost; cells are a partition column of a saved index."""
        if search == "scan":
            return self.segments
        if search == "cells" and self.cells is not None:
            return self.segments.where(F.col("cell").isin(self.cells.within(probes)))
        if search == "codes" and self.codes is not None:
            bound = [self.codes.least_distance(F.col("code"), F.col("code_error"), p) <= radius for p, radius in probes]
            return self.segments.where(reduce(lambda a, b: a | b, bound, F.lit(False)))
        raise ValueError(f"the index has no {search}")

    def save(self, path: str) -> TwoLevelIndex:
        """Both levels as Parquet, dealt by doc_key so that a document's rows lie together; segments by cell, if there are cells."""
        spark = self.docs.sparkSession
        for name, frame in (("docs", self.docs), ("segments", self.segments)):
            writer = frame.repartition("doc_key").sortWithinPartitions("doc_key").write.mode("overwrite")
            (writer.partitionBy("cell") if "cell" in frame.columns else writer).parquet(f"{path}/{name}")
        kept = [("cells", json.dumps([self.cells.centres, self.cells.radii]))] if self.cells else []
        kept += [("codes", json.dumps(self.codes.books))] if self.codes else []
        spark.createDataFrame(kept, "name string, content string").coalesce(1).write.mode("overwrite").parquet(f"{path}/search")
        return TwoLevelIndex.load(spark, path, self.model)

    @staticmethod
    def load(spark: SparkSession, path: str, model: Callable[[list[str]], list[list[float]]] | None = None) -> TwoLevelIndex:
        kept = {r.name: json.loads(r.content) for r in spark.read.parquet(f"{path}/search").collect()}
        cells, codes = Cells(*kept["cells"]) if "cells" in kept else None, Codes(kept["codes"]) if "codes" in kept else None
        return TwoLevelIndex(spark.read.parquet(f"{path}/docs"), spark.read.parquet(f"{path}/segments"), model, cells, codes)

    def save_tables(self, name: str, buckets: int = 200) -> TwoLevelIndex:
        """Both levels as tables in buckets of doc_key: joins between them shuffle nothing."""
        spark = self.docs.sparkSession
        for level, frame in (("docs", self.docs), ("segments", self.segments)):
            frame.write.mode("overwrite").bucketBy(buckets, "doc_key").sortBy("doc_key").saveAsTable(f"{name}_{level}")
        return replace(self, docs=spark.table(f"{name}_docs"), segments=spark.table(f"{name}_segments"), texts=None)


#: Probes that may be broadcast; more are refused, to be asked in blocks.
MOST_PROBES = 100_000


def few(probes: DataFrame) -> DataFrame:
    """Probes for a broadcast, their number checked."""
    if probes.limit(MOST_PROBES + 1).count() > MOST_PROBES:
        raise ValueError(f"more than {MOST_PROBES} probes: ask them in blocks")
    return F.broadcast(probes)


class ExactIndex:
    """Every vector against every probe, in blocks: vectors(key, vec array<float>)."""

    def __init__(self, vectors: DataFrame, key: str = "vec_id", column: str = "embedding"):
        self.vectors = vectors.select(F.col(key).alias("key"), F.col(column).alias("vec"))

    def range(self, probes: DataFrame, radius: float) -> DataFrame:
        """(probe, key, dist) within the radius; probes(probe, pvec) may be many."""
        return blocks.within(self.vectors, _asked(probes), radius)

    def topk(self, probes: DataFrame, k: int) -> DataFrame:
        """(probe, rank, key, dist): the k nearest; each task keeps k a probe, and only these are shuffled."""
        return _nearest(blocks.topk(self.vectors, _asked(probes), k), k)


def _asked(probes: DataFrame, *more: str) -> DataFrame:
    return probes.select("probe", F.col("pvec").alias("vec"), *more)


def _nearest(hits: DataFrame, k: int) -> DataFrame:
    """Of hits(probe, dist, key) the k least of each probe, null distances last."""
    from pyspark.sql import Window

    order = Window.partitionBy("probe").orderBy(F.col("dist").asc_nulls_last(), F.col("key").asc_nulls_last())
    return hits.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("probe", "rank", "key", "dist")


class IVFIndex:
    """Inverted file: k-means cells, of which a probe reads the nprobe nearest. Cells may be a partition column of the stored table."""

    def __init__(self, vectors: DataFrame, nlist: int = 16, seed: int = 1, key: str = "vec_id", column: str = "embedding", sample: int = 100_000):
        base = vectors.select(F.col(key).alias("key"), F.col(column).alias("vec"))
        fit = base.orderBy(F.xxhash64("key")).limit(sample).select(array_to_vector(F.col("vec").cast("array<double>")).alias("features"))
        self.centres = [c.tolist() for c in KMeans(k=nlist, seed=seed, maxIter=15).fit(fit).clusterCenters()]
        self.vectors = blocks.nearest(base, "vec", self.centres, 1, "cells").select("key", "vec", F.col("cells")[0].alias("cell"))

    def topk(self, probes: DataFrame, k: int, nprobe: int = 4) -> DataFrame:
        asked = blocks.nearest(probes, "pvec", self.centres, nprobe, "cells")
        nlist = len(self.centres)

        def of_cells(rows, v, asked, p):
            """Of a block's rows those of each cell, against the probes that ask for it."""
            wanted = np.zeros((len(asked), nlist), bool)
            for i, own in enumerate(asked["cells"]):
                wanted[i, own] = True
            cell = rows["cell"].to_numpy()
            for c in np.unique(cell):
                own, columns = np.flatnonzero(cell == c), np.flatnonzero(wanted[:, c])
                for low in range(0, len(own), 2048):
                    yield own[low : low + 2048], columns, None

        return _nearest(blocks.topk(self.vectors, _asked(asked, "cells"), k, of_cells), k)


class PQIndex:
    """Product quantisation: m sub-vectors, each a code of ks centres. The vectors stay beside the codes."""

    def __init__(self, vectors: DataFrame, m: int = 8, ks: int = 16, seed: int = 1, key: str = "vec_id", column: str = "embedding", sample: int = 100_000):
        base = vectors.select(F.col(key).alias("key"), F.col(column).cast("array<double>").alias("vec"))
        rows = cut(base.orderBy(F.xxhash64("key")).limit(sample), "pq-sample")
        self.m, self.width, self.books = m, len(rows.select("vec").first()[0]) // m, []
        for j in range(m):
            part = rows.select(array_to_vector(F.slice("vec", j * self.width + 1, self.width)).alias("features"))
            self.books.append([c.tolist() for c in KMeans(k=ks, seed=seed, maxIter=15).fit(part).clusterCenters()])
        code = lambda j: F.array_min(F.array(*[F.struct(euclid(F.slice("vec", j * self.width + 1, self.width), F.lit(c)).alias("d"), F.lit(i).cast("byte").alias("c")) for i, c in enumerate(self.books[j])]))["c"]
        self.coded = base.withColumn("code", F.array(*[code(j) for j in range(m)]))
        self.codes = self.coded.select("key", "code")

    def meant(self, codes: Column) -> Column:
        """What a code stands for: its centres, one after the other."""
        return F.flatten(F.transform(codes, lambda c, j: F.element_at(F.element_at(F.lit(self.books), j + 1), c.cast("int") + 1)))

    def topk(self, probes: DataFrame, k: int, shortlist: int | None = None, sample: int = 20_000) -> DataFrame:
        """Nearest by asymmetric distance: the probe is exact, the stored vector its code. With a shortlist, about so many nearest by code are ranked by
        their exact distance: those within the reach that holds this share of a bounded sample of codes, of least hashes (of all, if they are no more)."""
        if shortlist is None:
            return _nearest(blocks.topk(self.codes.select("key", self.meant(F.col("code")).alias("vec")), _asked(probes), k), k)
        n = self.codes.count()
        drawn = np.array([r.code for r in self.codes.where("code is not null").orderBy(F.xxhash64("key"), "key").limit(sample).collect()], int)
        books = [np.array(b) for b in self.books]
        stand = lambda codes: np.concatenate([books[j][codes[:, j]] for j in range(len(books))], 1)
        place = min(len(drawn), max(k, math.ceil(max(k, shortlist) * len(drawn) / n))) - 1

        def reaches(batches):
            import pyarrow as pa

            points = stand(drawn)
            for batch in batches:
                vecs = np.array(batch.column("vec").to_pylist(), float)
                reach = [np.partition(blocks.squares(points, vecs[low : low + 128])[0], place, axis=0)[place] for low in range(0, len(vecs), 128)]
                yield pa.RecordBatch.from_arrays([batch.column("probe"), batch.column("vec"), pa.array(np.concatenate(reach) if reach else np.array([]), pa.float64())], ["probe", "vec", "reach"])

        kind = probes.schema["probe"].dataType.simpleString()
        asked = probes.select("probe", F.col("pvec").cast("array<double>").alias("vec")).where("vec is not null").mapInArrow(reaches, f"probe {kind}, vec array<double>, reach double")

        def by_code(rows, v, asked, p):
            """Pairs whose codes are within the probe's reach."""
            points, reach = stand(np.array(rows["code"].tolist(), int)), asked["reach"].to_numpy()
            for own, columns, _ in blocks.everything(rows, v, asked, p):
                yield own, columns, blocks.squares(points[own], p)[0] <= reach[None] + 1e-9

        return _nearest(blocks.topk(self.coded.where("vec is not null"), asked, k, by_code), k)


class LSHIndex:
    """Random projections in buckets, for joins of large vector sets."""

    def __init__(self, vectors: DataFrame, bucket_length: float = 1.0, tables: int = 8, seed: int = 1, key: str = "vec_id", column: str = "embedding"):
        self.vectors = vectors.select(F.col(key).alias("key"), array_to_vector(F.col(column).cast("array<double>")).alias("features"))
        self.model = BucketedRandomProjectionLSH(inputCol="features", outputCol="hashes", bucketLength=bucket_length, numHashTables=tables, seed=seed).fit(self.vectors)

    def join(self, radius: float) -> DataFrame:
        """(a, b, dist) of pairs nearer than the radius that share a bucket. Vectors lie in the order of their buckets, so blocks without a common one are passed over;
        each pair of blocks meets once, however many buckets its vectors share."""
        hashes = [vector_to_array(F.col("hashes")[j])[0].cast("long") for j in range(self.model.getNumHashTables())]
        placed = self.model.transform(self.vectors).select("key", vector_to_array("features").alias("vec"), F.array(*hashes).alias("hashes"))
        made = cut(blocks.packed(placed.orderBy("hashes", "key")), "lsh-blocks")
        return blocks.joined(made, radius, self.vectors.count(), self.vectors.schema["key"].dataType.simpleString())


def kmeans_centres(points: Sequence[Sequence[float]], k: int = 3, iterations: int = 20, counts: Sequence[int] | None = None) -> list[list[float]]:
    """Centres of few points on the driver: farthest-first start from the point nearest the mean, then Lloyd steps. Fewer distinct points than k: each is one. A point counts `counts` times."""
    x = np.unique(np.asarray(points, float), axis=0)
    if len(x) <= k:
        return x.tolist()
    chosen = [int(((x - x.mean(0)) ** 2).sum(1).argmin())]
    while len(chosen) < k:
        chosen.append(int(np.min([((x - x[c]) ** 2).sum(1) for c in chosen], axis=0).argmax()))
    full, centres, weights = np.asarray(points, float), x[chosen], np.ones(len(points)) if counts is None else np.asarray(counts, float)
    for _ in range(iterations):
        own = ((full[:, None, :] - centres[None]) ** 2).sum(2).argmin(1)
        new = np.array([np.average(full[own == j], axis=0, weights=weights[own == j]) if (own == j).any() else centres[j] for j in range(k)])
        if np.allclose(new, centres):
            break
        centres = new
    return centres.tolist()
