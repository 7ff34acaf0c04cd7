"""Segments, vectors and radii in Arrow batches against the same as Columns."""

from pyspark.sql import functions as F

from docspj.functions.text import distance_to, embed, norm2
from docspj.operators import batches
from docspj.operators.index import TwoLevelIndex
from docspj.operators.segments import segment, summarise
from docspj.sources.corpora import profiles

ODD = [
    "", " ", None, "One. Two! Three? four", "3.14 is 3.14.\tThe  THE the.\nNext\n\nline", "Ärger über STRASSE 12a-b;  edge . ΣΑΣ İx.", "...", "#1 #2 1234", "a b\x0bc\x0cd\re", " odd  \u0085x\u0085.",
    "same words here. same words here. same words here. other things there. " * 40, "٠١ n² Ⅷ _x_ é.", "\U0001f600 smile. \U00010400 deseret",
]


def test_batches_say_what_columns_say(spark, sf_dir):
    odd = spark.createDataFrame([("P", f"odd:{i}", "x", t) for i, t in enumerate(ODD)], "corpus string, doc_key string, domain string, text string")
    docs = odd.unionByName(profiles(spark, sf_dir))
    entries = lambda df: sorted((r.doc_key, r.seg_no, r.text, r.n_tokens, r.first_sent, r.last_sent, sorted(r.vec.items()), r.n2) for r in df.collect())
    for options in ({"sim_threshold": 0.6}, {"sim_threshold": 0.25, "max_tokens": 12}):
        plain = segment(docs, **options).withColumn("vec", embed(F.col("text"))).withColumn("n2", norm2(F.col("vec")))
        assert entries(batches.segmented(docs, **options)) == entries(plain)
    made = {r.doc_key: (r.vec, r.n2) for r in batches.embedded(docs.select("doc_key", "text"), "text").collect()}
    assert made == {r.doc_key: (r.vec, r.n2) for r in docs.select("doc_key", embed(F.col("text")).alias("vec")).withColumn("n2", norm2(F.col("vec"))).collect()}
    leads = {r.doc_key: (r.vecs, r.n2s) for r in batches.led(docs).collect()}
    plain = summarise(docs, "lead").select("doc_key", embed(F.col("summary")).alias("vec")).withColumn("n2", norm2(F.col("vec")))
    assert leads == {r.doc_key: ([r.vec], [r.n2]) for r in plain.collect()}


def test_near_segments_are_those_of_the_distance(spark, sf_dir):
    segments = batches.segmented(profiles(spark, sf_dir), 0.6).unionByName(spark.createDataFrame([("P", "none", 0, "x", 1, 0, 0, {}, 0), ("P", "null", 0, "x", 1, 0, 0, None, None)], "corpus string, doc_key string, seg_no int, text string, n_tokens int, first_sent int, last_sent int, vec map<int,int>, n2 bigint"))
    unit = lambda at: [1.0 if i == at else 0.0 for i in range(256)]
    asked = [("a", [unit(3), unit(70)], 1.1), ("b", [unit(9)], 1.25), ("none", [], 1.0), ("all", [unit(1)], 1.42)]
    got = {(r.doc_key, r.seg_no, n) for r in batches.near(segments, asked).collect() for n, _, _ in asked if r[f"near_{n}"]}
    rows = segments.select("doc_key", "seg_no", *[F.least(F.lit(9.0), *[distance_to(F.col("vec"), F.col("n2"), c) for c in own], F.lit(9.0)).alias(n) for n, own, _ in asked], "n2").where("n2 is not null").collect()
    assert got == {(r.doc_key, r.seg_no, n) for r in rows for n, _, radius in asked if r[n] <= radius} and {n for *_, n in got} == {"a", "b", "all"}


def test_one_pass_makes_both_levels(spark, sf_dir):
    """An index of one pass is that of two, documents without a sentence included, and segments are near by their texts as by their vectors."""
    odd = spark.createDataFrame([("P", f"odd:{i}", "x", t) for i, t in enumerate(ODD)], "corpus string, doc_key string, domain string, text string")
    docs = odd.unionByName(profiles(spark, sf_dir))
    one, two = TwoLevelIndex.of_texts(docs, sim_threshold=0.6), TwoLevelIndex.build(docs, "lead", sim_threshold=0.6)
    rows = lambda df: sorted(str(tuple(sorted(x.items()) if isinstance(x, dict) else x for x in r)) for r in df.collect())
    tops = [sorted((r.doc_key, [sorted(v.items()) for v in r.vecs], r.n2s) for r in x.docs.collect()) for x in (one, two)]
    assert tops[0] == tops[1] and {"odd:0", "odd:2"} <= {k for k, *_ in tops[0]}
    assert rows(one.segments) == rows(two.segments.select(one.segments.columns))
    unit = lambda at: [1.0 if i == at else 0.0 for i in range(256)]
    asked = [("a", [unit(3), unit(70)], 1.1), ("b", [unit(9)], 1.25), ("none", [], 1.0), ("all", [unit(1)], 1.42)]
    assert rows(batches.near_texts(one.texts, asked)) == rows(batches.near(two.segments, asked)) != []
