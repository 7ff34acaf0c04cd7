"""Answers over all of the input, held against other ways to them on small tables."""

import datetime

import pytest
from pyspark.sql import functions as F

from docspj.functions.text import embed, norm2, sentences
from docspj.model import Attribute
from docspj.operators.index import ExactIndex, PQIndex, TwoLevelIndex, kmeans_centres
from docspj.operators.retrieval import fit_probes, hashed, mean_embedding, retrieve, sample_docs
from docspj.operators.segments import segment_located
from docspj.registry import methods
from docspj.registry.suites import answer
from docspj.sources.corpora import truth
from docspj.workload import by_name


@pytest.fixture(scope="module")
def few_orders(spark, tmp_path_factory):
    """Seven orders, whose keys share no divisor and go past two millions, with lines for some."""
    d = str(tmp_path_factory.mktemp("orders"))
    day = datetime.datetime(1995, 3, 1)
    keys = [1, 7, 15, 151, 1500, 1_800_001, 2_000_003]
    orders = [(k, 1 + i % 2, "OFP"[i % 3], 1000.5 * (i + 1), day + datetime.timedelta(i), "1-URGENT") for i, k in enumerate(keys)]
    lines = [(k, j, 2.0 * j, "R" if k == 7 else "N", day + datetime.timedelta(20 + j)) for k in keys[:5] for j in (1, 2)]
    tables = {
        "orders": (orders, "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp, o_orderpriority string"),
        "lineitem": (lines, "l_orderkey long, l_linenumber int, l_quantity double, l_returnflag string, l_shipdate timestamp"),
        "customer": ([(1, "Customer#1", 0, 5.0, "BUILDING"), (2, "Customer#2", 0, 6.0, "MACHINERY")], "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string"),
        "nation": ([(0, "NATION_0", 0)], "n_nationkey int, n_name string, n_regionkey int"),
        "region": ([(0, "AFRICA")], "r_regionkey int, r_name string"),
        "supplier": ([(1, "Supplier#1", 0, 1.0)], "s_suppkey long, s_name string, s_nationkey int, s_acctbal double"),
        "documents": ([(1, "A sentence that stands about here and has enough letters to be one.", "en", "s", 1)], "doc_id long, text string, lang string, source string, n_chars long"),
    }
    for name, (rows, schema) in tables.items():
        spark.createDataFrame(rows, schema).coalesce(1).write.parquet(f"{d}/{name}.parquet")
    return d, orders


def test_every_order_has_a_dossier(spark, few_orders):
    d, orders = few_orders
    rows = {r.order_key: r for r in truth(spark, d, "order").collect()}
    assert sorted(rows) == [o[0] for o in orders]
    assert all((rows[k].n_lines, rows[k].total_qty) == (2, 6) for k in (1, 7, 15, 151, 1500)) and rows[2_000_003].n_lines == 0
    assert [k for k in rows if rows[k].any_returned] == [7]


def test_dossier_query_answers_over_every_order(spark, few_orders):
    d, orders = few_orders
    assert sorted(r.order_order_key for r in answer(spark, d, by_name("C01")).collect()) == [o[0] for o in orders if o[2] == "F"] == [7, 1500]


def test_all_evidence_of_the_sample_counts(spark):
    """10,050 documents, of which the last by key is the only one worded another way."""
    text = F.when(F.col("id") == 10_049, F.lit("Much later and far away some heavy crate of the size is 7")).otherwise(F.lit("part size is 5"))
    rows = spark.range(10_050).select(F.lit("x").alias("corpus"), F.format_string("d%05d", "id").alias("doc_key"), text.alias("text")).withColumn("vec", embed(F.col("text"))).withColumn("n2", norm2(F.col("vec")))
    docs = rows.select("corpus", "doc_key", F.array("vec").alias("vecs"), F.array("n2").alias("n2s"))
    index = TwoLevelIndex(docs, rows.select("corpus", "doc_key", F.lit(0).alias("seg_no"), "text", F.lit(4).alias("n_tokens"), "vec", "n2"))
    size = Attribute("size", "part size", "bigint", r"size is ([0-9]+)")
    assert sample_docs(docs, 1.0).count() == 10_050
    probes = fit_probes(index, [size], rate=1.0, tau0=2.0)
    assert probes.sample_docs == probes.evidence["size"] == 10_050 and len(probes.centres["size"]) == 2
    assert retrieve(index, [size], probes).where("doc_key = 'd10049' and cost_size > 0").count() == 1


def test_counted_points_are_as_many_points():
    points = [[0.0, 0.0], [0.0, 1.0], [5.0, 5.0], [6.0, 5.0], [9.0, 0.0]]
    counts = [1, 3, 2, 2, 4]
    repeated = [p for p, n in zip(points, counts, strict=True) for _ in range(n)]
    for a, b in zip(kmeans_centres(points, 2, counts=counts), kmeans_centres(repeated, 2), strict=True):
        assert a == pytest.approx(b)


def test_searches_reach_the_recall(spark, sf_dir):
    row = methods.ivf_recall(spark, sf_dir).first()
    v = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    probes = methods._asked(spark, sf_dir)
    assert row.recall >= 0.9 and row.n == 10 * v.where("vec_id % 20 = 0").count()
    index = PQIndex(v, 4, 4)
    exact = {(r.probe, r.rank, r.key) for r in ExactIndex(v).topk(probes, 5).collect()}
    assert {(r.probe, r.rank, r.key) for r in index.topk(probes, 5, v.count()).collect()} == exact


def test_star_join_counts_each_side_alone(spark, tmp_path):
    """Nations of one name count together, those without a partner not at all, and no customer is paired with a supplier."""
    from docspj.registry import relational

    tables = {
        "region": ("r_regionkey long, r_name string", [(0, "A"), (1, None)]),
        "nation": ("n_nationkey long, n_name string, n_regionkey long", [(1, "x", 0), (2, "x", 0), (3, "y", 1), (4, "z", 0), (5, "v", 0)]),
        "customer": ("c_custkey long, c_nationkey long", [(1, 1), (2, 1), (2, 2), (None, 3), (4, 4)]),
        "supplier": ("s_suppkey long, s_nationkey long", [(1, 1), (2, 2), (1, 2), (7, 3), (8, 5), (9, None)]),
    }
    for name, (schema, rows) in tables.items():
        spark.createDataFrame(rows, schema).write.parquet(f"{tmp_path}/{name}.parquet")
    made = relational.queries()["join_star_four"](spark, str(tmp_path))
    assert {tuple(r) for r in made.collect()} == {("A", "x", 2, 2), (None, "y", 0, 1)}
    plan = made._jdf.queryExecution().optimizedPlan().toString()
    assert not [x for x in plan.splitlines() if "Join Inner" in x and "c_custkey" in x and "s_suppkey" in x] and "Expand" not in plan


def test_sentences_lose_blanks_of_all_kinds(spark):
    """As trim in SQL does: separators of space at the edges go, other white space stays, also before a line separator."""
    texts = ["\xa0\n\na.", "?　\n", "x  ", " e\x85 ", "a.\xa0b", "\t\x1c y"]
    rows = spark.createDataFrame(list(enumerate(texts)), "i long, text string").select("i", sentences(F.col("text")).alias("s")).orderBy("i").collect()
    assert [r.s for r in rows] == [["a."], ["?"], ["x  "], ["e\x85"], ["a.\xa0b"], ["\t\x1c y"]]


def test_attribute_without_evidence_is_still_found(spark):
    """No sampled document holds the code; the one document that does is read all the same."""
    rows = [("T", f"doc:{i}", f"Item {i} has colour red{i % 3}.\nplain words of no use {i}") for i in range(40)]
    attributes = [Attribute("colour", "colour of the item", "string", r"colour (red[0-9])"), Attribute("code", "code of the item", "string", r"zz=([a-z]+)")]

    def index(docs):
        made = spark.createDataFrame(docs, "corpus string, doc_key string, text string")
        return TwoLevelIndex.build(made, "lead", segments=segment_located(made))

    sampled = {r.doc_key for r in fit_probes(index(rows), attributes, rate=0.05, least=2).sample.collect()}
    holder = next(k for _, k, _ in rows if k not in sampled)
    own = index([(c, k, t + "\nhttp://x.y/?zz=feed" if k == holder else t) for c, k, t in rows])
    probes = fit_probes(own, attributes, rate=0.05, least=2)
    assert probes.evidence["code"] == 0
    assert [r.doc_key for r in retrieve(own, attributes, probes).where("text_code like '%zz=feed%'").collect()] == [holder]


def test_dossiers_are_not_written(spark, few_orders, monkeypatch):
    """Sentences are read in their document's row: none is written, and contexts are those of written segments."""
    from docspj.operators.retrieval import full_texts, retrieve_located, sampled_texts
    from docspj.registry import suites
    from docspj.sources.corpora import specs

    written = []
    monkeypatch.setattr(suites, "cut", lambda df, label="cut": written.append((label, df.columns)) or df)
    monkeypatch.setattr(suites, "_held", {})
    index = suites.sentence_index(spark, few_orders[0], "C")
    assert written == [("docs", ["corpus", "doc_key"])]
    attributes = [specs("C")["order"][n] for n in ("order_key", "n_lines", "any_returned")]
    apart = TwoLevelIndex(index.docs, index.segments)
    columns = sorted(retrieve_located(apart, attributes).columns)
    rows = lambda df: sorted(tuple(r) for r in df.select(*columns).collect())
    assert rows(retrieve_located(index, attributes)) == rows(retrieve_located(apart, attributes))
    some = index.docs.orderBy("doc_key").limit(3).select("doc_key")
    texts = lambda df: sorted((r.doc_key, r.text, r.n_tokens) for r in df.collect())
    assert texts(sampled_texts(index, some)) == texts(full_texts(index.segments.join(some, "doc_key", "left_semi")))


def test_mean_embedding_is_that_of_a_query(spark):
    """Of many keys at once, the means of a query's normalised texts, as query_embedding makes them on the driver; an empty text counts for nothing."""
    texts = {"a": ["red house", "red car 17"], "b": ["blue"], None: ["old red boat", "boat"]}
    rows = spark.createDataFrame([(k, t) for k, own in texts.items() for t in [*own, ""]], "kind string, text string").withColumn("vec", embed(F.col("text"))).withColumn("n2", norm2(F.col("vec")))
    got = {(r.kind, r.bucket): r.value for r in mean_embedding(rows, "kind").collect()}
    mean = lambda own: [sum(x) / len(own) for x in zip(*map(hashed, own), strict=True)]
    want = {(k, i): x for k, own in texts.items() for i, x in enumerate(mean(own)) if x}
    assert got.keys() == want.keys() and all(abs(got[x] - want[x]) < 1e-12 for x in want)
