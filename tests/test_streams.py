"""Streams give what batches give."""

import pytest
from pyspark.sql import functions as F

from docspj.model import ge, normalise
from docspj.streaming import first_arrivals, join_arrivals, maintain_index, running_selectivity, spend, spend_by_session, spend_by_window, standing_filter


@pytest.fixture(scope="module")
def feed(spark, tmp_path_factory):
    folder = str(tmp_path_factory.mktemp("feed"))
    events = spark.read.parquet("/root/testdata/sf0.001/events.parquet").orderBy("ts").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value")
    events.repartitionByRange(4, "ts").write.mode("overwrite").parquet(folder)
    stream = lambda: spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(folder)
    return events, stream


def drain(df, name, tmp_path, mode="append"):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start()
    q.awaitTermination(120)
    return df.sparkSession.table(name)


def test_spend_by_window(feed, tmp_path):
    events, stream = feed
    got = drain(spend_by_window(spend(stream()), "1 day", late="40 days"), "spend", tmp_path, "update")
    last = got.groupBy("span", "attr").agg(F.max("calls").alias("calls"))
    want = spend(events).groupBy(F.window("ts", "1 day").alias("span"), "attr").agg(F.count(F.lit(1)).alias("calls"))
    assert want.exceptAll(last).count() == 0
    assert drain(spend_by_window(spend(stream()), "2 hours", "1 hour", "40 days"), "slide", tmp_path, "update").count() > 0
    assert drain(spend_by_session(spend(stream()), late="1 hour"), "sessions", tmp_path).count() > 0


def test_standing_filter_and_selectivity(feed, tmp_path):
    events, stream = feed
    tree = normalise(ge("value", 50))
    cost = {"value": F.col("user_id") % 9 + 1}
    one = lambda df: standing_filter(df, tree, {"value": F.col("value")}, cost, {1: 0.5}).select("event_id", "tokens")
    assert one(events).exceptAll(drain(one(stream()), "standing", tmp_path)).count() == 0
    p = drain(running_selectivity(stream(), tree, {"value": F.col("value")}, 1e9), "chances", tmp_path, "update").orderBy(F.desc("n")).first()
    assert p.n == pytest.approx(events.count(), rel=1e-3) and p.p == pytest.approx(events.where("value >= 50").count() / events.count(), rel=1e-3)


def test_arrivals(feed, tmp_path):
    events, stream = feed
    twice = stream().unionByName(stream())
    assert drain(first_arrivals(twice.select("event_id", "ts"), ["event_id"], "40 days"), "firsts", tmp_path).count() == events.count()
    labels = stream().select("user_id", F.col("ts").alias("label_ts"), F.col("event_id").alias("label"))
    got = drain(join_arrivals(stream().select("user_id", "ts", "event_id"), labels, "user_id", "1 hour", "40 days"), "joined", tmp_path)
    want = events.alias("a").join(events.alias("b"), F.expr("a.user_id = b.user_id and b.ts >= a.ts and b.ts <= a.ts + interval 1 hour"))
    assert got.count() == want.count()


def test_index_grows_with_arrivals(spark, tmp_path):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").limit(40).select(F.lit("raw").alias("corpus"), F.col("doc_id").cast("string").alias("doc_key"), "text")
    docs.repartition(3).write.parquet(str(tmp_path / "docs"))
    stream = spark.readStream.schema(docs.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "docs"))
    maintain_index(stream, str(tmp_path / "index"), str(tmp_path / "ck")).awaitTermination(120)
    rows = spark.read.parquet(str(tmp_path / "index"))
    assert rows.select("doc_key").distinct().count() == docs.where("text <> ''").count()
