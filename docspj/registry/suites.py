"""The query suites through the engine, and plain SQL on the base columns for the same answers."""

from __future__ import annotations

from collections.abc import Callable
from datetime import date

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from docspj.engine import Engine, Settings
from docspj.functions.text import n_tokens, sentences
from docspj.model import Expr, Leaf, Query
from docspj.operators.index import TwoLevelIndex
from docspj.operators.segments import segment_located
from docspj.session import cut
from docspj.sources.corpora import corpus, distractors, dossier_keys, dossiers, specs
from docspj.workload import SUITES, by_name

_held: dict[tuple, TwoLevelIndex] = {}


def sentence_index(spark: SparkSession, sf_dir: str, suite: str) -> TwoLevelIndex:
    """Documents and their sentences (lines, for pages), without vectors; written once a session. Of dossiers and pages only keys are written: their
    sentences would take several times the tables' own size, and are made where they are read, inside their document's row."""
    key = (spark.sparkContext.applicationId, sf_dir, suite, "sentences")
    if key not in _held:
        sizes = F.aggregate("parts", F.lit(0).cast("bigint"), lambda n, s: n + n_tokens(s))
        pool = spark.createDataFrame([(distractors(spark, sf_dir).first().pool,)], "pool array<string>") if suite == "C" else None

        def parts(only: DataFrame | None = None, shown: Callable[[Column], Column] | None = None) -> DataFrame:
            cut_up = F.split("text", r"\n") if suite == "G" else sentences(F.col("text"))
            made = dossiers(spark, sf_dir, only=only, pool=pool, shown=shown) if suite == "C" else corpus(spark, sf_dir, suite, only=only)
            if "parts" not in made.columns:
                made = made.select("corpus", "doc_key", cut_up.alias("parts"), F.lit(0).alias("left_out"))
            return made.select("corpus", "doc_key", "parts", (sizes + F.col("left_out")).alias("n_tokens"))

        rows = parts().select("corpus", "doc_key", F.posexplode("parts").alias("seg_no", "text")).withColumn("n_tokens", n_tokens(F.col("text")))
        keys = cut(dossier_keys(spark, sf_dir) if suite == "C" else corpus(spark, sf_dir, suite).select("corpus", "doc_key"), "docs")
        _held[key] = TwoLevelIndex(keys, cut(rows, "segments")) if suite == "P" else TwoLevelIndex(keys, rows, parts=parts)
    return _held[key]


def vector_index(spark: SparkSession, sf_dir: str, suite: str = "P", regime: str = "pattern", summary: str = "lead") -> TwoLevelIndex:
    """The two-level index of a suite; written once a session."""
    key = (spark.sparkContext.applicationId, sf_dir, suite, regime, summary)
    if key not in _held:
        docs = corpus(spark, sf_dir, suite, regime)
        # Pages are parted by their markup, a line each, as a full stop in a title parts nothing. Hashed vectors of short facts share many words: only close neighbours make one segment.
        if suite != "G" and summary == "lead":
            _held[key] = TwoLevelIndex.of_texts(docs, sim_threshold=0.6)
            return _held[key]
        made = TwoLevelIndex.build(docs, summary, segments=segment_located(docs)) if suite == "G" else TwoLevelIndex.build(docs, summary, sim_threshold=0.6)
        _held[key] = TwoLevelIndex(cut(made.docs, "docs"), cut(made.segments, "segments"))
    return _held[key]


def answer(spark: SparkSession, sf_dir: str, q: Query, **settings) -> DataFrame:
    """The tuples of a suite's query; columns are table_attribute."""
    retrieval = settings.pop("retrieval", "located")
    index = sentence_index(spark, sf_dir, q.name[0]) if retrieval in ("located", "full") else vector_index(spark, sf_dir, q.name[0])
    found = Engine(index, specs(q.name[0]), Settings(retrieval=retrieval, **settings)).run(q).tuples
    return found.select(*[F.col(f"`{t}.{a}`" if len(q.tables) > 1 else a).alias(f"{t}_{a}") for t, a in q.select])


_NATION = """select n.n_nationkey, n.n_name as name, r.r_name as region_name,
  (select s.s_name from supplier s where s.s_nationkey = n.n_nationkey order by s.s_suppkey limit 1) as owner_name,
  (select count(*) from customer c where c.c_nationkey = n.n_nationkey) as n_customers,
  (select count(*) from supplier s where s.s_nationkey = n.n_nationkey) as n_suppliers
  from nation n join region r on r.r_regionkey = n.n_regionkey"""
#: The virtual tables as SQL over the base columns.
TABLES_SQL = {
    "customer": "select c_name as name, n_name as nation_name, c_acctbal as balance, c_mktsegment as segment from customer join nation on n_nationkey = c_nationkey",
    "supplier": "select s_name as name, n_name as nation_name, s_acctbal as balance from supplier join nation on n_nationkey = s_nationkey",
    "part": "select p_name as name, p_brand as brand, p_type as type, cast(p_size as bigint) as size, p_retailprice as price from part",
    "nation": f"select name, region_name, owner_name, n_customers from ({_NATION}) x",
    "region": f"select region_name as name, count(*) as n_nations, cast(sum(n_customers) as bigint) as n_customers, cast(sum(n_suppliers) as bigint) as n_suppliers from ({_NATION}) x group by region_name",
    "page": r"""select nullif(regexp_extract(url, '^(https?)://', 1), '') as scheme, nullif(regexp_extract(url, '^https?://([^/]+)', 1), '') as host,
  nullif(regexp_extract(url, '^https?://[^/]*?([a-z0-9-]+\.example\.[a-z]+|example\.[a-z]+)', 1), '') as site, nullif(regexp_extract(url, '^https?://[^/]*\.([a-z]+)/', 1), '') as tld,
  nullif(regexp_extract(url, '^https?://[^/]+/([a-z]{2})/', 1), '') as path_lang, cast(nullif(regexp_extract(url, '^https?://[^/]+/[a-z]{2}/([0-9]+)', 1), '') as bigint) as path_no,
  contains(url, '?') as has_query, nullif(regexp_extract(url, 'utm_source=([a-z]+)', 1), '') as utm_source, nullif(regexp_extract(html, '<html lang="([a-z]+)"', 1), '') as html_lang,
  nullif(regexp_extract(html, '<title>(.*?)</title>', 1), '') as title, nullif(regexp_extract(html, '<h1>(.*?)</h1>', 1), '') as h1,
  cast(nullif(regexp_extract(html, 'track\(([0-9]+)\)', 1), '') as bigint) as track_id,
  (length(html) - length(replace(html, '<li>', ''))) // 4 as nav_links, (length(html) - length(replace(html, '<p>', ''))) // 3 as n_paragraphs
  from pages""",
    "order": """select o.o_orderkey as order_key, o.o_orderstatus as status, o.o_orderpriority as priority, cast(o.o_orderdate as date) as order_date, o.o_totalprice as total_price,
  c.c_name as customer_name, coalesce(l.n, 0) as n_lines, coalesce(l.q, 0) as total_qty, l.d as last_ship_date, coalesce(l.r, 0) = 1 as any_returned
  from orders o left join customer c on c.c_custkey = o.o_custkey
  left join (select l_orderkey, count(*) as n, cast(sum(l_quantity) as bigint) as q, cast(max(l_shipdate) as date) as d, max(case when l_returnflag = 'R' then 1 else 0 end) as r from lineitem group by l_orderkey) l on l.l_orderkey = o.o_orderkey""",
}


def _literal(v: object) -> str:
    if isinstance(v, bool):
        return str(v).lower()
    if isinstance(v, date):
        return f"date '{v}'"
    return "'" + v.replace("'", "''") + "'" if isinstance(v, str) else str(v)


def where_sql(expr: Expr | None, table: str) -> str:
    if expr is None:
        return "true"
    if isinstance(expr, Leaf):
        a = f"d_{table}.{expr.attr}"
        if expr.op == "between":
            return f"{a} between {_literal(expr.args[0])} and {_literal(expr.args[1])}"
        if expr.op == "in":
            return f"{a} in ({', '.join(map(_literal, expr.args))})"
        return f"{a} {expr.op} {_literal(expr.args[0])}"
    return "(" + f" {expr.op} ".join(where_sql(c, table) for c in expr.children) + ")"


def query_sql(q: Query) -> str:
    """The query as an SPJ over the base columns."""
    with_ = ", ".join(f"t_{t} as ({TABLES_SQL[t]})" for t in q.tables)
    from_ = ", ".join(f"t_{t} d_{t}" for t in q.tables)
    conditions = [where_sql(q.where.get(t), t) for t in q.tables] + [f"d_{e.left}.{e.left_attr} = d_{e.right}.{e.right_attr}" for e in q.edges]
    chosen = ", ".join(f"d_{t}.{a} as {t}_{a}" for t, a in q.select)
    return f"with {with_} select {chosen} from {from_} where {' and '.join(conditions)}"


#: Queries whose evidence is fitted, by suite. A dossier suite's vectors take minutes to make, so its figures are an experiment's (README).
FITTED = ("P", "G")


def recall(q: Query) -> Callable[[SparkSession, str], DataFrame]:
    """(query, expected, wrong, reached) of a query through fitted probes: its true tuples, what it returned beside them, and whether nine tenths of them are there."""

    def of(s: SparkSession, d: str) -> DataFrame:
        from docspj.experiments import truth_of
        from docspj.metrics import scores

        true = truth_of(s, d, q)
        found = answer(s, d, q, retrieval="evidence").toDF(*true.columns)
        return scores(found, true).select(F.lit(q.name).alias("query"), F.col("expected").cast("bigint").alias("expected"), (F.col("returned") - F.col("hits")).cast("bigint").alias("wrong"), (F.col("recall") >= 0.9).alias("reached"))

    return of


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = {f"spj_{q.name}": (lambda s, d, q=q: answer(s, d, q)) for suite in SUITES.values() for q in suite()}
    for q in (q for suite in FITTED for q in SUITES[suite]()):
        found[f"spj_evidence_{q.name}"] = lambda s, d, q=q: answer(s, d, q, retrieval="evidence")
    return found | {f"recall_{q.name}": recall(q) for q in SUITES["P"]() if q.name in LOSSY} | {"join_adaptive_result": lambda s, d: answer(s, d, by_name("P24"))}


#: Queries that lose some tuples through fitted probes at sf0.01; their recall is a query of its own, beside the tuples.
LOSSY = ("P01", "P02", "P21")


def oracle_sql() -> dict[str, str]:
    found = {f"spj_{q.name}": query_sql(q) for suite in SUITES.values() for q in suite()}
    found |= {f"spj_evidence_{q.name}": query_sql(q) for suite in FITTED for q in SUITES[suite]()}
    found |= {f"recall_{q.name}": f"select '{q.name}' as query, count(*) as expected, cast(0 as bigint) as wrong, true as reached from ({query_sql(q)}) x" for q in SUITES["P"]() if q.name in LOSSY}
    return found | {"join_adaptive_result": query_sql(by_name("P24"))}
