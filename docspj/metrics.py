"""Accuracy by tuples, token cost, latency."""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def scores(result: DataFrame, truth: DataFrame) -> DataFrame:
    """One row (returned, expected, hits, precision, recall, f1): a returned tuple counts if every cell is as in a tuple of the truth, each of these once.

    Both empty: 1, 1, 1. One empty: 0, 0, 0.
    """
    names = truth.columns
    count = lambda df, n: df.select(*[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(names)]).groupBy(*[f"c{i}" for i in range(len(names))]).agg(F.count(F.lit(1)).alias(n))
    got, want = count(result, "g"), count(truth, "w").withColumnsRenamed({f"c{i}": f"t{i}" for i in range(len(names))})
    same = [F.col(f"c{i}").eqNullSafe(F.col(f"t{i}")) for i in range(len(names))]
    sums = got.join(want, same, "full_outer").agg(
        F.coalesce(F.sum("g"), F.lit(0)).alias("returned"), F.coalesce(F.sum("w"), F.lit(0)).alias("expected"), F.coalesce(F.sum(F.least(F.coalesce("g", F.lit(0)), F.coalesce("w", F.lit(0)))), F.lit(0)).alias("hits")
    )
    none = (F.col("returned") == 0) & (F.col("expected") == 0)
    part = lambda n: F.when(none, 1.0).when(F.col(n) == 0, 0.0).otherwise(F.col("hits") / F.greatest(F.col(n), F.lit(1)))
    with_parts = sums.withColumns({"precision": part("returned"), "recall": part("expected")})
    p, r = F.col("precision"), F.col("recall")
    return with_parts.withColumn("f1", F.when(p + r > 0, 2 * p * r / (p + r)).otherwise(0.0))


def macro(rows: Sequence[dict]) -> dict:
    """Means over queries."""
    return {k: sum(r[k] for r in rows) / len(rows) for k in rows[0]} if rows else {}


def token_cost(tokens: int, documents: int) -> float:
    """Tokens in and out, sampling included, a document."""
    return tokens / documents if documents else 0.0


def cost_gap(expected: float, spent: float) -> float:
    """Share by which what was spent lies above (or, negative, below) what was expected."""
    return (spent - expected) / expected if expected else 0.0


def latency(action: Callable[[], object], documents: int) -> tuple[object, float]:
    """What an action returns, and its seconds a document."""
    began = time.perf_counter()
    found = action()
    return found, (time.perf_counter() - began) / max(1, documents)


def modelled_latency(calls: int, tokens: int, documents: int, seconds_a_call: float = 0.4, seconds_a_token: float = 2e-4) -> float:
    """Seconds a document that a served model would take: a fixed part of each call and a part of each token."""
    return (calls * seconds_a_call + tokens * seconds_a_token) / max(1, documents)


def retrieval_scores(retrieved: DataFrame, truth: DataFrame, keys: Sequence[str]) -> DataFrame:
    """Share of true segments (or documents) retrieved, and of retrieved ones that are true."""
    hit = retrieved.select(*keys).distinct().withColumn("r", F.lit(1)).join(truth.select(*keys).distinct().withColumn("t", F.lit(1)), list(keys), "full_outer")
    return hit.agg(F.try_divide(F.count_if(F.col("r").isNotNull() & F.col("t").isNotNull()), F.count("t")).alias("recall"), F.try_divide(F.count_if(F.col("r").isNotNull() & F.col("t").isNotNull()), F.count("r")).alias("precision"))
