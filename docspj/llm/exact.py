"""Exact duplicates with a heavy-hitter split.

Texts are equal when they are identical without white space; SHA-256 of what is left is the digest. Misra-Gries summaries, one a
partition and merged by adding counters, find every digest with more than about 2/k of the rows; their exact winners and sizes,
at most k+1 rows, are broadcast and marked in place. All other digests, each of a bounded share of the rows, are shuffled.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from docspj.llm.common import SPACE_CHARS, scratch


def normal_text(text: Column) -> Column:
    """The text without white space; null is empty."""
    return F.translate(F.coalesce(text, F.lit("")), SPACE_CHARS, "")


def misra_gries(counters: dict[int, int], keys: np.ndarray, k: int) -> dict[int, int]:
    """counters with keys counted in, k at most: what the (k+1)-th largest counter has is taken from all."""
    for key, n in zip(*np.unique(keys, return_counts=True), strict=True):
        counters[int(key)] = counters.get(int(key), 0) + int(n)
    if len(counters) > k:
        cut = sorted(counters.values(), reverse=True)[k]
        counters = {key: n - cut for key, n in counters.items() if n > cut}
    return counters


def frequent_keys(df: DataFrame, column: str, k: int) -> list[int]:
    """At most k+1 values of a long column, all that more than 2/(k+1) of its rows hold among them. The driver gets only these."""

    def of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counters: dict[int, int] = {}
        for batch in batches:
            counters = misra_gries(counters, batch.column(0).to_numpy(zero_copy_only=False), k)
        yield pa.RecordBatch.from_pydict({"key": pa.array(list(counters), pa.int64()), "n": pa.array(list(counters.values()), pa.int64())})

    counted = df.select(column).mapInArrow(of, "key long, n long")
    top = counted.groupBy("key").agg(F.sum("n").alias("n")).where("n > 0").orderBy(F.desc("n"), "key").limit(k + 1)
    return [r.key for r in top.collect()]


def exact_duplicates(docs: DataFrame, k: int = 512) -> DataFrame:
    """(doc_id, keep_id, group_size, kept, text_sha256) of every row of docs(doc_id, text).

    Of equal texts the row of most code points stays, then that of least doc_id; null ids come last. A null text is empty; empty texts are
    equal. Rows that repeat the id that stays are each kept. An empty table gives an empty result. Other columns are ignored.
    """
    rows = docs.select("doc_id", F.coalesce(F.char_length("text"), F.lit(0)).alias("points"), F.unhex(F.sha2(normal_text(F.col("text")).cast("binary"), 256)).alias("digest"))
    rows = scratch(rows.withColumn("short", F.xxhash64("digest")), "digests")
    winner = F.min(F.struct((-F.col("points")).alias("less"), F.col("doc_id").isNull().alias("last"), "doc_id")).alias("best")
    heavy = frequent_keys(rows, "short", k)
    spark = docs.sparkSession
    is_heavy = F.col("short").isin(heavy) if heavy else F.lit(False)

    def decided(part: DataFrame) -> DataFrame:
        return part.groupBy("digest").agg(winner, F.count(F.lit(1)).alias("group_size")).select("digest", F.col("best.doc_id").alias("keep_id"), "group_size")

    verified = scratch(decided(rows.where(is_heavy)), "heavy")
    marked = rows.where(is_heavy).join(F.broadcast(verified), "digest")
    light = rows.where(~is_heavy)
    rest = light.join(decided(light), "digest")
    kept = F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept")
    return marked.unionByName(rest).select("doc_id", "keep_id", "group_size", kept, F.lower(F.hex("digest")).alias("text_sha256"))
