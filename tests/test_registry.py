"""The driver's contract: names, columns, and a sample of queries against their SQL."""

import duckdb
import pytest

import __spark_entry__ as entry
from docspj.registry import methods, relational, suites

SF = "/root/testdata/sf0.001"
SAMPLE = ["order_and_priority", "order_tree", "lazy_ledger_or", "order_arms_cost", "join_plan_costs", "hash_embedding", "vector_exact_topk", "spj_P11", "spj_P21", "spj_G05", "spj_C04", "asof_events", "band_join_part", "ledger_cube", "tuple_prf1"]


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        c.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return c


def rows_of(frame):
    show = lambda v: "" if v is None or v != v else repr(round(float(v), 5)) if isinstance(v, (int, float)) and not isinstance(v, bool) else str(v)
    frame = frame[sorted(frame.columns)].astype(object).where(frame.notna(), None)
    return sorted(tuple(show(v) for v in r) for r in frame.values.tolist())


def test_names():
    known, sql = entry.queries(), entry.oracle_sql()
    assert set(sql) <= set(known)
    own = (suites, methods, relational)
    assert sum(len(m.queries()) for m in own) == len({n for m in own for n in m.queries()})


@pytest.mark.parametrize("name", SAMPLE)
def test_query_and_sql_agree(spark, duck, name):
    got = entry.queries()[name](spark, SF).toPandas()
    want = duck.execute(entry.oracle_sql()[name]).fetchdf()
    assert sorted(got.columns) == sorted(want.columns) and rows_of(got) == rows_of(want)


def test_entry(spark):
    assert entry.entry(spark).count() == 15


def test_plans(spark):
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    scan = plan(relational.scan_documents(spark, SF))
    assert "PushedFilters" in scan and "text" not in scan.split("ReadSchema")[1]
    assert "LeftSemi" in plan(relational.in_semijoin(spark, SF)) and "SortMergeJoin" in plan(relational.join_orders_lineitem(spark, SF))
    assert "Exchange" not in plan(methods.ledger(methods.AND3)(spark, SF)) and "Cartesian" not in plan(methods.vector_range(spark, SF))
