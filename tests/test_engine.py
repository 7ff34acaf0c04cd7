"""Text, index, retrieval, engine, baselines and measures on the smallest tables."""

import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from docspj.baselines import NAMES, baseline, best_sentence, induce
from docspj.engine import Engine, Settings, best_order, left_deep_orders
from docspj.experiments import compare_joins, measure, planning_time, report, truth_of
from docspj.functions import udfs
from docspj.functions.text import cosine, distance, embed, euclid, l2n, n_tokens, norm2, python_embed, sentences
from docspj.metrics import macro, modelled_latency, retrieval_scores, scores, token_cost
from docspj.model import Attribute
from docspj.operators.extractors import ExtractionCache, approx_from_sample, cost_with_cache, noisy, read_batch
from docspj.operators.index import ExactIndex, IVFIndex, TwoLevelIndex, kmeans_centres
from docspj.operators.retrieval import analyse, doc_distance, extract, fit_gamma, fit_probes, fit_tau, query_embedding, retrieve, retrieve_docs, sample_docs, synthesise_evidence
from docspj.operators.segments import segment, segment_by_window, segment_fixed, summarise
from docspj.session import cut
from docspj.sources.corpora import corpus, profiles, spec, specs, truth
from docspj.sources.datasource import register, write_bucketed, write_partitioned
from docspj.workload import SUITES, by_name, group, make_joins, make_queries

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def index(spark):
    made = TwoLevelIndex.build(profiles(spark, SF))
    return TwoLevelIndex(cut(made.docs), cut(made.segments))


def test_text_functions(spark):
    row = spark.createDataFrame([("One two. Three!  Four\nfive 12 of", None)], "t string, n string").select(n_tokens(F.col("t")).alias("n"), n_tokens(F.col("n")).alias("z"), sentences(F.col("t")).alias("s"), embed(F.col("t")).alias("v")).first()
    assert (row.n, row.z, row.s) == (7, 0, ["One two.", "Three!", "Four", "five 12 of"])
    assert row.v == python_embed("One two. Three!  Four\nfive 12 of")


def test_distances(spark):
    rng = np.random.default_rng(1)
    rows = [(rng.normal(size=6).tolist(), rng.normal(size=6).tolist()) for _ in range(20)]
    d = spark.createDataFrame(rows, "a array<double>, b array<double>")
    for r in d.select(euclid(l2n(F.col("a")), l2n(F.col("b"))).alias("e"), cosine(F.col("a"), F.col("b")).alias("c")).collect():
        assert r.e**2 == pytest.approx(2 - 2 * r.c)
    sparse = spark.createDataFrame([({1: 1, 2: 2}, {1: 1, 2: 2}), ({1: 1}, {2: 5}), ({1: 1}, {})], "a map<int,int>, b map<int,int>")
    assert [round(r[0], 6) for r in sparse.select(distance(F.col("a"), F.col("b"), norm2(F.col("a")), norm2(F.col("b")))).collect()] == [0.0, round(math.sqrt(2), 6), round(math.sqrt(2), 6)]


def test_segments(spark):
    docs = spark.createDataFrame([("x", "d1", "Red cars drive fast. Red cars drive slowly. Blue fish swim deep. Blue fish swim there."), ("x", "d2", ""), ("x", "d3", "Alone here.")], "corpus string, doc_key string, text string")
    for mode in ("previous", "running"):
        rows = sorted((r.doc_key, r.seg_no, r.text, r.first_sent, r.last_sent) for r in segment(docs, mode).collect())
        assert rows == [("d1", 0, "Red cars drive fast. Red cars drive slowly.", 0, 1), ("d1", 1, "Blue fish swim deep. Blue fish swim there.", 2, 3), ("d3", 0, "Alone here.", 0, 0)]
    assert segment(docs, "percentile", q=0.5).count() >= 2
    assert [r.n_tokens for r in segment(docs, max_tokens=4).where("doc_key = 'd1'").collect()] == [4, 4, 4, 4]
    wide = {(r.doc_key, r.pos): r.seg_no for r in segment_by_window(docs).collect()}
    assert wide == {("d1", 0): 0, ("d1", 1): 0, ("d1", 2): 1, ("d1", 3): 1, ("d3", 0): 0}
    fixed = [(r.seg_no, r.n_tokens) for r in segment_fixed(docs, 6, 2).where("doc_key = 'd1'").collect()]
    assert fixed == [(0, 6), (1, 6), (2, 6), (3, 4)]
    short = {r.doc_key: (r.sentences, r.summary) for r in summarise(docs, "frequency", 2).collect()}
    assert len(short["d1"][0]) == 2 and short["d3"] == (["Alone here."], "Alone here.") and short["d2"][0] == []
    assert {r.doc_key: r.summary for r in summarise(docs, "lead").collect()} == {"d1": "Red cars drive fast.", "d2": "", "d3": "Alone here."}


def test_windows_and_folds_cut_alike(spark):
    docs = corpus(spark, SF, "raw").limit(40)
    folds = segment(docs, max_tokens=10**9).groupBy("doc_key").agg(F.count(F.lit(1)).alias("n"))
    windows = segment_by_window(docs).groupBy("doc_key").agg((F.max("seg_no") + 1).alias("n"))
    assert folds.exceptAll(windows).count() == 0 and folds.count() == windows.count()


def test_centres_and_thresholds():
    rng = random.Random(4)
    points = [[rng.random() for _ in range(5)] for _ in range(30)]
    centres = kmeans_centres(points, 3)
    gamma = fit_gamma(points)
    assert all(min(math.dist(x, c) for c in centres) <= gamma for x in points)
    assert kmeans_centres(points[:2], 3) == sorted(points[:2]) and len(kmeans_centres([points[0]] * 5, 3)) == 1
    assert fit_gamma([points[0]]) == pytest.approx(0.1) and fit_tau([]) == 1.45 and fit_tau([0.3, 0.7]) == pytest.approx(0.8) and fit_tau([1.4]) == 1.45
    assert len(synthesise_evidence(Attribute("age", "player's age"), 20)) == 20


def test_retrieval_keeps_what_the_sample_showed(spark, index):
    t = spec("part")
    attributes = [t["size"], t["price"]]
    probes = fit_probes(index, attributes, rate=0.2, required="size")
    assert probes.evidence["size"] > 3 and probes.sample_tokens > 0 and probes.thresholds.tau <= 1.45
    query = query_embedding(attributes)
    found = retrieve_docs(index.docs, query, 1.45)
    sample = sample_docs(found, 0.2)
    rows = retrieve(index, attributes, probes).join(sample.select("doc_key"), "doc_key")
    seen = analyse(index.segments, sample, attributes).where("has_size").select("doc_key").distinct()
    assert seen.join(rows.where(F.col("cost_size") > 0), "doc_key", "left_anti").count() == 0
    refined = index.docs.withColumn("doc_dist", doc_distance(query)).where(F.col("doc_dist") <= probes.thresholds.tau)
    assert refined.count() < index.docs.count() and refined.where("doc_key like 'part:%'").count() == 200


@pytest.mark.parametrize("suite", ["P", "G", "C"])
def test_patterns_read_the_truth(spark, suite):
    docs = corpus(spark, SF, suite)
    for name, t in specs(suite).items():
        if name == "page":
            continue
        rows = docs.where(F.col("domain") == name).select("doc_key", *[extract(F.col("text"), a).alias(a.name) for a in t.attributes])
        assert rows.exceptAll(truth(spark, SF, name).select(*rows.columns)).count() == 0
    for regime in ("named", "disjoint") if suite == "P" else ():
        t = spec("part", regime)
        rows = profiles(spark, SF, regime, ("part",)).select("doc_key", *[extract(F.col("text"), a).alias(a.name) for a in t.attributes])
        assert rows.exceptAll(truth(spark, SF, "part").select(*rows.columns)).count() == 0


def same(run, spark, q):
    want = truth_of(spark, SF, q)
    got = run.tuples.select(*[c for t, c in q.select]) if len(q.tables) == 1 else run.tuples.toDF(*[f"{t}.{a}" for t, a in q.select])
    s = scores(got, want).first()
    return s["precision"], s["recall"], s["expected"]


@pytest.mark.parametrize("name", ["P02", "P07", "P11", "P14", "P21", "P23"])
def test_located_retrieval_answers_exactly(spark, index, name):
    q = by_name(name)
    run = Engine(index, specs("P"), Settings(retrieval="located")).run(q)
    assert same(run, spark, q)[:2] == (1.0, 1.0)
    if name == "P11":
        text = "select name from part where type = 'SMALL' and size >= 30 and price <= 950"
        assert Engine(index, specs("P"), Settings(retrieval="located")).sql(text).count() == run.tuples.count() == 15
    full = Engine(index, specs("P"), Settings(retrieval="full", order="written", join="pushdown")).run(q)
    assert same(full, spark, q)[:2] == (1.0, 1.0) and full.total > run.total


@pytest.mark.parametrize("mode", ["pushdown", "random", "adaptive", "fixed:nation,customer"])
def test_join_modes_give_the_same_tuples(spark, index, mode):
    q = by_name("P21")
    run = Engine(index, specs("P"), Settings(retrieval="located", join=mode)).run(q)
    assert same(run, spark, q)[:2] == (1.0, 1.0)
    if mode.startswith("fixed"):
        assert run.steps == ["nation", "customer"]


def test_joins_save_tokens(spark, index):
    q = by_name("P21")
    engine = Engine(index, specs("P"), Settings(retrieval="located"))
    ours, best = engine.run(q), best_order(engine, q)
    engine.settings.join = "pushdown"
    push = engine.run(q)
    assert best.total <= ours.total < push.total
    assert len(left_deep_orders(by_name("P25"))) > 4
    rows = compare_joins(index, [["nation-region"]], 2)
    assert all(r["optimal"] <= r["adaptive"] for r in rows) and "nation-region-0" in report(rows)


def test_join_without_partners_reads_nothing_more(spark, index):
    from docspj.model import eq
    from docspj.workload import JOINS
    from docspj.model import Query

    q = Query("none", ("customer", "nation"), (("customer", "name"),), {"nation": eq("region_name", "NOWHERE")}, (JOINS["customer-nation"],))
    run = Engine(index, specs("P"), Settings(retrieval="located", join="fixed:nation,customer")).run(q)
    assert run.tuples.count() == 0


@pytest.mark.parametrize("name", NAMES)
def test_baselines_run(spark, index, name):
    q = by_name("P11")
    run = baseline(name, index, specs("P")).run(q)
    row = measure(spark, SF, q, run, 1.0)
    assert 0 <= row["f1"] <= 1
    if name == "full_scan":
        assert row["f1"] == 1.0
    if name == "complete":
        assert row["f1"] > 0.9
    if name == "reader":
        assert run.total == 0


def test_best_sentence_and_induced_patterns(spark, index):
    near = best_sentence(index, spec("part")["size"]).where("doc_key = 'part:1'").first()
    assert near.text
    assert induce([("the size is 12 units", "12"), ("the size is 9 units", "9")]) == r"the\ size\ is\s+(-?[0-9]+(?:\.[0-9]+)?)" and induce([]) is None


def test_measures(spark):
    a = spark.createDataFrame([(1, "x"), (1, "x"), (2, None)], "k int, v string")
    b = spark.createDataFrame([(1, "x"), (2, None), (3, "z")], "k int, v string")
    s = scores(a, b).first()
    assert (s["hits"], s["precision"], s["recall"]) == (2, 2 / 3, 2 / 3)
    none = a.limit(0)
    assert tuple(scores(none, none).first())[3:] == (1.0, 1.0, 1.0) and tuple(scores(none, b).first())[3:] == (0.0, 0.0, 0.0)
    assert macro([{"f1": 1.0}, {"f1": 0.0}]) == {"f1": 0.5} and token_cost(10, 4) == 2.5 and modelled_latency(1, 0, 1) == 0.4
    r = retrieval_scores(a, b, ["k"]).first()
    assert (r.recall, r.precision) == (2 / 3, 1.0)


def test_noise_and_cache(spark, tmp_path):
    asked = spark.createDataFrame([("d1", "age", "age is 41 years"), ("d2", "age", "no"), ("d3", "age", "boom")], "doc_key string, attr string, text string")

    def reader(attr, text):
        if text == "boom":
            raise RuntimeError("model down")
        return next((w for w in text.split() if w.isdigit()), None)

    cache = ExtractionCache(spark, str(tmp_path / "cache"))
    ask = lambda rows: read_batch(rows, reader, retries=1)
    first, paid = cache.read(asked, ask)
    assert {r.doc_key: r.value for r in first.collect()} == {"d1": "41", "d2": None, "d3": None} and paid == 7
    again, paid = cache.read(asked, ask)
    assert paid == 0 and again.count() == 3
    costs = asked.select("doc_key", "attr", F.lit(9).cast("bigint").alias("tokens")).unionByName(spark.createDataFrame([("d9", "age", 5)], "doc_key string, attr string, tokens long"))
    assert {r.doc_key: r.tokens for r in cost_with_cache(costs, cache).collect()} == {"d1": 0, "d2": 0, "d3": 0, "d9": 5}
    a = Attribute("n", "", "bigint", r"n=([0-9]+)")
    texts = spark.range(400).select(F.concat(F.lit("n="), "id", F.lit(" "), F.repeat(F.lit("pad "), F.when(F.col("id") < 200, 0).otherwise(12000))).alias("t"), "id")
    right = texts.select("id", noisy()(F.col("t"), a).isNotNull().alias("ok")).collect()
    assert sum(r.ok for r in right if r.id < 200) > 1.3 * sum(r.ok for r in right if r.id >= 200)
    est = approx_from_sample(spark.createDataFrame([(1.0,), (3.0,)], "v double"), "v", 10).first()
    assert est["sum"] == 20.0 and est["half_width"] > 0


def test_vector_indexes(spark):
    v = spark.read.parquet(f"{SF}/embeddings.parquet")
    probes = v.where("vec_id < 5").select(F.col("vec_id").alias("probe"), F.col("embedding").alias("pvec"))
    exact = {(r.probe, r.key) for r in ExactIndex(v).topk(probes, 4).collect()}
    rows = {r.vec_id: np.array(r.embedding) for r in v.collect()}
    for p in range(5):
        near = sorted(rows, key=lambda k: (round(float(np.sqrt(((rows[k].astype(float) - rows[p].astype(float)) ** 2).sum())), 9), k))[:4]
        assert {k for q, k in exact if q == p} == set(near)
    ivf = IVFIndex(v, 8)
    assert {(r.probe, r.key) for r in ivf.topk(probes, 4, nprobe=8).collect()} == exact


def test_generated_queries():
    assert [q.name for q in make_queries("part", 3)] == [q.name for q in make_queries("part", 3)]
    assert {group(q) for q in make_queries("customer", 10)} == {"1", "2-3", "4+"}
    assert len({q.name for s in SUITES.values() for q in s()}) == 50
    assert all(q.graph.tables for q in make_joins(["customer-nation", "nation-region"], 4))
    rows = planning_time((2, 3, 4, 5, 6), (32,))
    assert rows[-1]["priority"] < 1


def test_sources_and_functions(spark, tmp_path):
    (tmp_path / "a").mkdir()
    (tmp_path / "a" / "x.txt").write_text("First one. Second one.")
    (tmp_path / "y.md").write_text("Alone.")
    register(spark)
    docs = spark.read.format("docspj_corpus").option("corpus", "mine").load(str(tmp_path))
    assert {(r.corpus, r.doc_key) for r in docs.collect()} == {("mine", "a/x.txt"), ("mine", "y.md")}
    udfs.register(spark)
    assert [r.sentence for r in spark.sql("select sentence from sentences_of('First one. Second one.') order by pos").collect()] == ["First one.", "Second one."]
    assert spark.sql("select * from segments_of('A b. C d. E f.', 4)").count() == 2
    model = udfs.callable_embedder(lambda texts: [[float(len(t)), 1.0] for t in texts])
    assert [list(r[0]) for r in docs.select(model(F.col("text")).alias("v")).collect()] == [[22.0, 1.0], [6.0, 1.0]]
    mean = spark.createDataFrame([([1.0, 3.0],), ([3.0, 5.0],)], "v array<double>").agg(udfs.centroid("v")).first()[0]
    assert list(mean) == [2.0, 4.0]
    rows = spark.createDataFrame([("d", "age", "1"), ("d", "name", "x")], "doc_key string, attr string, value string")
    write_partitioned(rows, str(tmp_path / "out"), "attr")
    assert {p.name for p in (tmp_path / "out").glob("attr=*")} == {"attr=age", "attr=name"}
    write_bucketed(rows, "docspj_cache", buckets=2)
    joined = spark.table("docspj_cache").hint("merge").join(spark.table("docspj_cache"), "doc_key")
    assert joined.count() == 4 and "Exchange hashpartitioning(doc_key" not in joined._jdf.queryExecution().executedPlan().toString()
    spark.sql("drop table docspj_cache")
