"""Dossiers' sentences: those that many documents share are judged once, and nothing else changes."""

import datetime

import pytest
from pyspark.sql import functions as F

from docspj.operators.index import TwoLevelIndex
from docspj.operators.retrieval import extract, full_texts, retrieve_located, sampled_texts, shown
from docspj.registry import suites
from docspj.sources.corpora import specs

POOL = ["Once again the order processing status is quite unknown to all here.", "Another sentence that stands about here and has letters enough.", "The last of these sentences says nothing at all of any order, it seems."]


@pytest.fixture(scope="module", params=[POOL, POOL[1:], []], ids=["held", "not held", "none"])
def index(request, spark, tmp_path_factory):
    d, day = str(tmp_path_factory.mktemp("dossiers")), datetime.datetime(1995, 3, 1)
    tables = {
        "orders": ([(k, 1 + k % 3, "OFP"[k % 3], 10.5 * k, day, "odd one. And! More" if k == 4 else "1-URGENT") for k in range(1, 13)], "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp, o_orderpriority string"),
        "lineitem": ([(k, j, 2.0 * j, "NR"[k % 2], day) for k in range(1, 9) for j in (1, 2)], "l_orderkey long, l_linenumber int, l_quantity double, l_returnflag string, l_shipdate timestamp"),
        "customer": ([(1, "Customer\n#1", 0), (2, " customer? #2", 0)], "c_custkey long, c_name string, c_nationkey int"),
        "nation": ([(0, "NATION_0", 0)], "n_nationkey int, n_name string, n_regionkey int"), "region": ([(0, "AFRICA")], "r_regionkey int, r_name string"),
        "supplier": ([(1, "Supplier#1", 0)], "s_suppkey long, s_name string, s_nationkey int"), "documents": ([(0, "x", "en"), *((i, s, "en") for i, s in enumerate(request.param, 1))], "doc_id long, text string, lang string"),
    }
    for name, (rows, schema) in tables.items():
        spark.createDataFrame(rows, schema).coalesce(1).write.parquet(f"{d}/{name}.parquet")
    return request.param, suites.sentence_index(spark, d, "C")


def test_shared_sentences_are_judged_once(index):
    """Contexts are those of written segments, also where shared sentences hold an attribute and facts have ends inside; the text that a task makes lacks the others."""
    pool, index = index
    attributes = [specs("C")["order"][n] for n in ("order_key", "status", "priority", "customer_name", "n_lines", "last_ship_date")]
    apart = TwoLevelIndex(index.docs, index.segments)
    columns = sorted(retrieve_located(apart, attributes).columns)
    rows = lambda df: sorted(tuple(r) for r in df.select(*columns).collect())
    got = rows(retrieve_located(index, attributes))
    assert len(got) == 12 and got == rows(retrieve_located(apart, attributes))
    assert (POOL[0] in str(got)) == (POOL[0] in pool)
    made = {r.doc_key: r.parts for r in index.parts(None, shown(attributes)).collect()}
    assert all(len(p) < 15 for p in made.values()) if POOL[0] not in pool else all(POOL[0] in p and POOL[1] not in p for p in made.values())


def test_sample_without_shared_sentences(index):
    """A rule finds in what is left of a sampled text what it finds in all of it, and the tokens are those of all of it."""
    _, index = index
    attributes = [specs("C")["order"][n] for n in ("order_key", "status", "total_price", "n_lines", "any_returned")]
    some = index.docs.where("doc_key <> 'order:3'").select("doc_key")
    read = lambda df: sorted(str(tuple(r)) for r in df.select("doc_key", "n_tokens", *[extract(F.col("text"), a) for a in attributes]).collect())
    got = read(sampled_texts(index, some, attributes))
    assert len(got) == 11 and got == read(full_texts(index.segments.join(some, "doc_key", "left_semi")))


def test_statements_that_cannot_hold_what_is_asked_are_left_out(index):
    """Of a document whose values are plain come the statements asked for alone; where a value has an end of a sentence in it, its statement comes too."""
    pool, index = index
    asked = [specs("C")["order"][n] for n in ("order_key", "n_lines")]
    made = {r.doc_key: r.parts for r in index.parts(None, shown(asked)).collect()}
    facts = {k: [s for s in p if s not in pool] for k, p in made.items()}
    # Order 2 is of no known customer, order 3 of one with a line feed in the name; order 4 has ends of sentences in its priority.
    assert len(facts["order:2"]) == 2 and any("Customer" in s for s in facts["order:3"]) and any("More" in s for s in facts["order:4"])
    assert all("status" not in s and "total price" not in s for p in facts.values() for s in p)
