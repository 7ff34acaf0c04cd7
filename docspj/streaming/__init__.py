"""Streams: an index that grows with arriving documents, standing filters, running statistics, token spend."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.streaming.query import StreamingQuery

from docspj.functions.text import embed, n_tokens, norm2
from docspj.model import Expr, attributes_of, leaves, test
from docspj.operators.lazy import fold_executor, planned
from docspj.operators.segments import segment
from docspj.sources.datasource import each_batch


def maintain_index(docs: DataFrame, path: str, checkpoint: str) -> StreamingQuery:
    """Segments of arriving docs(corpus, doc_key, text) with their vectors; a batch that is repeated overwrites its own folder."""
    rows = segment(docs).withColumn("vec", embed(F.col("text"))).withColumn("n2", norm2(F.col("vec")))
    return rows.writeStream.foreachBatch(each_batch(path)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def standing_filter(docs: DataFrame, expr: Expr, values: dict, cost: dict, p: dict[int, float]) -> DataFrame:
    """Arriving documents that pass, each tested in its own order: stateless, so it runs in a stream as in a batch."""
    return fold_executor(planned(docs, expr, cost, p), expr, values, cost).where("kept")


def running_selectivity(events: DataFrame, expr: Expr, values: dict, half_life: float = 1000.0) -> DataFrame:
    """(leaf, n, p): decayed share of arriving rows that satisfy each leaf, an update a batch."""
    tests = F.array(*[F.struct(F.lit(x.id).alias("leaf"), test(x, values[x.attr]).cast("int").alias("t")) for x in leaves(expr)])
    rows = events.select(F.inline(tests))

    def update(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, hits = state.get if state.exists else (0.0, 0.0)
        for f in frames:
            keep = 0.5 ** (len(f) / half_life)
            n, hits = n * keep + len(f), hits * keep + float(f["t"].sum())
        state.update((n, hits))
        yield pd.DataFrame({"leaf": [key[0]], "n": [n], "p": [hits / n if n else 0.0]})

    return rows.groupBy("leaf").applyInPandasWithState(update, "leaf int, n double, p double", "n double, hits double", "update", GroupStateTimeout.NoTimeout)


def spend_by_window(ledger: DataFrame, width: str = "1 hour", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Tokens by tumbling or sliding window of ts; rows later than `late` are dropped."""
    span = F.window("ts", width, slide) if slide else F.window("ts", width)
    return ledger.withWatermark("ts", late).groupBy(span.alias("span"), "attr").agg(F.sum("tokens").alias("tokens"), F.count(F.lit(1)).alias("calls"))


def spend_by_session(ledger: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    return ledger.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("span"), "attr").agg(F.sum("tokens").alias("tokens"))


def join_arrivals(docs: DataFrame, labels: DataFrame, key: str, within: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Documents (ts) with labels (label_ts) that arrive within an interval after them."""
    a, b = docs.withWatermark("ts", late), labels.withWatermark("label_ts", late).withColumnRenamed(key, f"label_{key}")
    return a.join(b, F.expr(f"{key} = label_{key} and label_ts >= ts and label_ts <= ts + interval {within}"))


def first_arrivals(docs: DataFrame, keys: list[str], late: str = "1 hour") -> DataFrame:
    return docs.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def near_centres(docs: DataFrame, centres: DataFrame, radius: float) -> DataFrame:
    """Arriving vectors against the few centres of a static table."""
    from docspj.functions.text import euclid

    return docs.crossJoin(F.broadcast(centres)).where(euclid("vec", "centre") <= radius)


def spend(events: DataFrame) -> DataFrame:
    """A ledger-like stream of the given events: a type is an attribute, a value a number of tokens."""
    return events.select(F.col("ts").cast("timestamp").alias("ts"), F.col("event_type").alias("attr"), F.col("value").cast("bigint").alias("tokens"))


__all__ = ["attributes_of", "first_arrivals", "join_arrivals", "maintain_index", "n_tokens", "near_centres", "running_selectivity", "spend", "spend_by_session", "spend_by_window", "standing_filter"]
