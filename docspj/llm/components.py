"""Connected components of an edge table by alternating large-star and small-star steps."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from docspj.llm.common import scratch


def _least_neighbour(links: DataFrame) -> DataFrame:
    """links(node, peer) -> links with the least of the node and its peers; counted before the shuffle, so a hot node is no hot task."""
    least = links.groupBy("node").agg(F.least(F.min("peer"), F.first("node")).alias("low"))
    return links.join(least, "node")


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.unionByName(edges.select(F.col("peer").alias("node"), F.col("node").alias("peer")))
    return _least_neighbour(both).where("peer > node").select(F.col("peer").alias("node"), F.col("low").alias("peer"))


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("node", "peer").alias("node"), F.least("node", "peer").alias("peer"))
    least = down.groupBy("node").agg(F.min("peer").alias("low"))
    moved = down.join(least, "node").where("peer <> low").select(F.col("peer").alias("node"), F.col("low").alias("peer"))
    return moved.unionByName(least.withColumnRenamed("low", "peer"))


def connected_components(edges: DataFrame, left: str = "a", right: str = "b") -> DataFrame:
    """edges(left, right) -> (id, component): the least id of each node's component, for nodes that have an edge.

    Edges with a null end and loops are ignored; repeated edges do no harm; an empty table gives an empty result. Each
    round is written to the shared folder, so a lost executor costs one round at most. The driver sees two numbers a round.
    """
    spark = edges.sparkSession
    now = edges.select(F.greatest(left, right).alias("node"), F.least(left, right).alias("peer")).where(
        f"`{left}` is not null and `{right}` is not null and `{left}` <> `{right}`"
    )
    now, seen = scratch(now.distinct(), "edges"), None
    while True:
        mark = now.agg(F.count(F.lit(1)), F.coalesce(F.bit_xor(F.xxhash64("node", "peer")), F.lit(0))).first()
        if mark == seen or mark[0] == 0:
            break
        seen = mark
        now = scratch(_small_star(_large_star(now).distinct()).where("node <> peer").distinct(), "stars")
    parts = now.groupBy("node").agg(F.min("peer").alias("component"))
    roots = now.select(F.col("peer").alias("node")).distinct().join(parts.select("node"), "node", "left_anti")
    return parts.unionByName(roots.withColumn("component", F.col("node"))).withColumnRenamed("node", "id")
