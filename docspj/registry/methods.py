"""Method-level queries: orders, ledgers, join costs, retrieval, index, measures; with SQL that takes another way to the same answer."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from docspj.functions.text import bucket, embed, n_tokens, norm2, sentences
from docspj.model import Expr, all_of, any_of, attributes_of, eq, ge, le, leaves, normalise
from docspj.operators.index import ExactIndex, IVFIndex, LSHIndex, PQIndex, few
from docspj.operators.lazy import TokenModel, fold_executor, planned
from docspj.operators.lazy import ledger as ledger_rows
from docspj.plans.ordering import expected_in_order, order_column, plan_node

#: Filters on `part` with chances as a sample would give them.
P = {1: 0.16, 2: 0.42, 3: 0.5, 4: 0.04}
VALUES = {"type": "p_type", "size": "p_size", "price": "p_retailprice", "brand": "p_brand"}
AND3 = normalise(all_of(eq("type", "SMALL"), ge("size", 30), le("price", 950)))
OR3 = normalise(any_of(eq("type", "SMALL"), ge("size", 30), le("price", 950)))
TREE4 = normalise(all_of(any_of(eq("type", "SMALL"), ge("size", 30)), any_of(le("price", 950), eq("brand", "Brand#4"))))
LEAF_SQL = {1: "p_type = 'SMALL'", 2: "p_size >= 30", 3: "p_retailprice <= 950", 4: "p_brand = 'Brand#4'"}
#: Pseudo-costs of reading an attribute of a part: whole numbers that any engine gets from the key.
COST = {"type": (17, 3, 90), "size": (29, 11, 60), "price": (7, 5, 120), "brand": (13, 1, 40)}


def cost(a: str) -> Column:
    m, b, n = COST[a]
    return ((F.col("p_partkey") * m + b) % n + 1).cast("bigint")


def cost_sql(a: str) -> str:
    m, b, n = COST[a]
    return f"cast((p_partkey * {m} + {b}) % {n} + 1 as bigint)"


def _part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/part.parquet")


def _columns(expr: Expr) -> tuple[dict[str, Column], dict[str, Column]]:
    names = attributes_of(expr)
    return {a: cost(a) for a in names}, {a: F.col(VALUES[a]) for a in names}


def best_cost(expr: Expr) -> Callable[[SparkSession, str], DataFrame]:
    """Expected tokens of the engine's order for each part."""
    return lambda s, d: _part(s, d).select("p_partkey", F.round(plan_node(expr, _columns(expr)[0], P)["c"], 6).alias("best"))


def ledger(expr: Expr, mode: str = "adaptive") -> Callable[[SparkSession, str], DataFrame]:
    def of(s: SparkSession, d: str) -> DataFrame:
        c, v = _columns(expr)
        done = fold_executor(planned(_part(s, d), expr, c, P, mode, averages={a: COST[a][2] / 2 for a in c}), expr, v, c)
        return done.select("p_partkey", "kept", "tokens", "calls")

    return of


def token_ledger(s: SparkSession, d: str) -> DataFrame:
    """Tokens in and out, and calls, by attribute and phase, with totals."""
    c, v = _columns(AND3)
    done = fold_executor(planned(_part(s, d), AND3, c, P), AND3, v, c)
    rows = ledger_rows(done, "p_partkey", c, v, "and3", model=TokenModel(prompt=12))
    return rows.rollup("phase", "attr").agg(F.sum("tokens_in").alias("tokens_in"), F.sum("tokens_out").alias("tokens_out"), F.sum("calls").cast("bigint").alias("calls"))


def _token_ledger_sql() -> str:
    names = {x.id: x.attr for x in leaves(AND3)}
    attr = "case leaf " + " ".join(f"when {i} then '{a}'" for i, a in names.items()) + " end"
    return f"""with l as ({_leaf_rows_sql(AND3)}),
r as (select *, row_number() over (partition by p_partkey order by (1 - p) / c desc, leaf) as k from l),
w as (select *, coalesce(min(t) over (partition by p_partkey order by k rows between unbounded preceding and 1 preceding), 1) as reached from r)
select phase, attr, cast(sum(c + 12) as bigint) as tokens_in, cast(count(*) as bigint) as tokens_out, cast(count(*) as bigint) as calls
from (select 'filter' as phase, {attr} as attr, c from w where reached = 1) x group by rollup (phase, attr)"""


def arms(s: SparkSession, d: str) -> DataFrame:
    """Tokens of each way of ordering over the whole table."""
    rows = None
    for mode in ("written", "random", "selectivity", "average_cost", "exhaustive", "adaptive"):
        one = ledger(AND3, mode)(s, d).agg(F.sum("tokens").alias("tokens"), F.sum("calls").alias("calls")).select(F.lit(mode).alias("arm"), "tokens", "calls")
        rows = one if rows is None else rows.unionByName(one)
    return rows


def _leaf_rows_sql(expr: Expr) -> str:
    return " union all ".join(f"select p_partkey, {x.id} as leaf, {cost_sql(x.attr)} as c, cast({P[x.id]} as double) as p, case when {LEAF_SQL[x.id]} then 1 else 0 end as t from part" for x in leaves(expr))


def _enumerated_sql(expr: Expr, through: str) -> str:
    """Least expected tokens over all orders, by listing them: the sort is not used."""
    ids = [x.id for x in leaves(expr)]
    n = len(ids)
    joins = " ".join(f"join l l{i} on l{i}.p_partkey = l0.p_partkey and l{i}.leaf not in ({', '.join(f'l{j}.leaf' for j in range(i))})" for i in range(1, n))
    terms = " + ".join(" * ".join([f"l{i}.c"] + [through.format(f"l{j}.p") for j in range(i)]) for i in range(n))
    return f"with l as ({_leaf_rows_sql(expr)}) select l0.p_partkey, round(min({terms}), 6) as best from l l0 {joins} group by l0.p_partkey"


def _tree_sql() -> str:
    """All eight contiguous orders of two disjunctions of two, priced one by one."""
    c = {i: cost_sql(a) for i, a in ((1, "type"), (2, "size"), (3, "price"), (4, "brand"))}
    pair = lambda x, y: f"(({c[x]}) + cast({1 - P[x]} as double) * ({c[y]}))"
    either = lambda x, y: 1 - (1 - P[x]) * (1 - P[y])
    left, right = f"least({pair(1, 2)}, {pair(2, 1)})", f"least({pair(3, 4)}, {pair(4, 3)})"
    return f"select p_partkey, round(least({left} + cast({either(1, 2)} as double) * {right}, {right} + cast({either(3, 4)} as double) * {left}), 6) as best from part"


def _flat_ledger_sql(op: str) -> str:
    """Ranks and running products in windows instead of a fold."""
    rank = "(1 - p) / c" if op == "and" else "p / c"
    goes_on = "t" if op == "and" else "1 - t"
    expr = AND3 if op == "and" else OR3
    kept = "min(t) = 1" if op == "and" else "max(t) = 1"
    return f"""with l as ({_leaf_rows_sql(expr)}),
r as (select *, row_number() over (partition by p_partkey order by {rank} desc, leaf) as k from l),
w as (select *, coalesce(min({goes_on}) over (partition by p_partkey order by k rows between unbounded preceding and 1 preceding), 1) as reached from r)
select p_partkey, {kept} as kept, cast(sum(c * reached) as bigint) as tokens, cast(sum(reached) as integer) as calls from w group by p_partkey"""


def _arms_sql() -> str:
    """Written, random and other fixed orders by nested cases; adaptive and exhaustive by windows."""
    import hashlib

    from docspj.plans.costs import order_tree

    attr = {x.id: x.attr for x in leaves(AND3)}
    fixed = {
        "written": [1, 2, 3],
        "random": sorted(attr, key=lambda i: hashlib.md5(f"0:{i}".encode()).hexdigest()),
        "selectivity": sorted(attr, key=lambda i: (P[i], i)),
        "average_cost": list(order_tree(AND3, {a: COST[a][2] / 2 for a in attr.values()}, P).order),
    }
    parts = []
    for arm, order in fixed.items():
        a, b, c = order
        t = f"{cost_sql(attr[a])} + case when {LEAF_SQL[a]} then {cost_sql(attr[b])} + case when {LEAF_SQL[b]} then {cost_sql(attr[c])} else 0 end else 0 end"
        n = f"1 + case when {LEAF_SQL[a]} then 1 + case when {LEAF_SQL[b]} then 1 else 0 end else 0 end"
        parts.append(f"select '{arm}' as arm, cast(sum({t}) as bigint) as tokens, cast(sum({n}) as bigint) as calls from part")
    for arm in ("exhaustive", "adaptive"):
        parts.append(f"select '{arm}' as arm, cast(sum(tokens) as bigint) as tokens, cast(sum(calls) as bigint) as calls from ({_flat_ledger_sql('and')}) x")
    return " union all ".join(parts)


def expected_written(expr: Expr) -> Callable[[SparkSession, str], DataFrame]:
    """Expected tokens of the order as written."""
    return lambda s, d: _part(s, d).select("p_partkey", F.round(expected_in_order(expr, [x.id for x in leaves(expr)], _columns(expr)[0], P), 6).alias("expected"))


def _expected_written_sql(expr: Expr, through: str) -> str:
    every, terms = leaves(expr), []
    for i, x in enumerate(every):
        terms.append(" * ".join([cost_sql(x.attr)] + [through.format(P[y.id]) for y in every[:i]]))
    return f"select p_partkey, round({' + '.join(terms)}, 6) as expected from part"


def argmin_order(s: SparkSession, d: str) -> DataFrame:
    """How many parts each order is best for."""
    order = order_column(AND3, _columns(AND3)[0], P)
    return _part(s, d).groupBy(F.array_join(F.transform(order, lambda i: i.cast("string")), ">").alias("plan")).agg(F.count(F.lit(1)).alias("n"))


def _argmin_sql() -> str:
    return f"""with l as ({_leaf_rows_sql(AND3)}) select plan, count(*) as n from (
select p_partkey, string_agg(cast(leaf as varchar), '>' order by (1 - p) / c desc, leaf) as plan from l group by p_partkey) x group by plan"""


def join_costs(s: SparkSession, d: str) -> DataFrame:
    """Expected cost of pushdown and of either IN plan for customers with a balance and nations with a region, from exact counts."""
    c, n, r = (s.read.parquet(f"{d}/{t}.parquet") for t in ("customer", "nation", "region"))
    left = c.select(F.lit(30).alias("filter_cost"), (F.col("c_custkey") % 40 + 10).alias("key_cost"), (F.col("c_acctbal") >= 9000).alias("ok"), F.col("c_nationkey").alias("k"))
    right = n.join(r, F.col("n_regionkey") == F.col("r_regionkey")).select(F.lit(50).alias("filter_cost"), F.lit(20).alias("key_cost"), (F.col("r_name") == "AFRICA").alias("ok"), F.col("n_nationkey").alias("k"))
    sums = lambda t, x: t.agg(F.sum("filter_cost").alias(f"f{x}"), F.sum("key_cost").alias(f"k{x}"), F.avg(F.col("ok").cast("double")).alias(f"p{x}"))
    met = lambda t, o, x: t.join(o.where("ok").select(F.col("k").alias("other")).distinct(), F.col("k") == F.col("other"), "left").agg(F.avg(F.col("other").isNotNull().cast("double")).alias(f"in{x}"))
    row = sums(left, 1).crossJoin(sums(right, 2)).crossJoin(met(right, left, 2)).crossJoin(met(left, right, 1))
    side = lambda x: f"f{x} + p{x} * k{x}"
    third = lambda x: f"least(k{x} + in{x} * f{x}, f{x} + p{x} * k{x})"
    return row.selectExpr(
        f"round({side(1)} + {side(2)}, 6) as pushdown", f"round({side(1)} + {third(2)}, 6) as left_first", f"round({side(2)} + {third(1)}, 6) as right_first", f"round({third(1)} + {third(2)}, 6) as ideal", f"{side(1)} < {side(2)} as left_chosen"
    )


JOIN_COSTS_SQL = """with a as (select 30 as f, c_custkey % 40 + 10 as k, c_acctbal >= 9000 as ok, c_nationkey as j from customer),
b as (select 50 as f, 20 as k, r_name = 'AFRICA' as ok, n_nationkey as j from nation join region on n_regionkey = r_regionkey),
s as (select (select sum(f) from a) as f1, (select sum(k) from a) as k1, (select avg(case when ok then 1.0 else 0.0 end) from a) as p1,
 (select sum(f) from b) as f2, (select sum(k) from b) as k2, (select avg(case when ok then 1.0 else 0.0 end) from b) as p2,
 (select avg(case when j in (select j from a where ok) then 1.0 else 0.0 end) from b) as in2, (select avg(case when j in (select j from b where ok) then 1.0 else 0.0 end) from a) as in1)
select round(cast(f1 + p1 * k1 + f2 + p2 * k2 as double), 6) as pushdown, round(cast(f1 + p1 * k1 + least(k2 + in2 * f2, f2 + p2 * k2) as double), 6) as left_first,
 round(cast(f2 + p2 * k2 + least(k1 + in1 * f1, f1 + p1 * k1) as double), 6) as right_first,
 round(cast(least(k1 + in1 * f1, f1 + p1 * k1) + least(k2 + in2 * f2, f2 + p2 * k2) as double), 6) as ideal, f1 + p1 * k1 < f2 + p2 * k2 as left_chosen from s"""


def join_in_filter(s: SparkSession, d: str) -> DataFrame:
    """Customers whose nation is among the values a filtered nation table left: a membership filter as a semi-join."""
    c, n = s.read.parquet(f"{d}/customer.parquet"), s.read.parquet(f"{d}/nation.parquet").where("n_regionkey = 2")
    return c.join(n, F.col("c_nationkey") == F.col("n_nationkey"), "left_semi").select("c_custkey", "c_name")


def hash_embedding(s: SparkSession, d: str) -> DataFrame:
    """Non-zero buckets of the hashed vector of each part's name and type."""
    vec = embed(F.concat_ws(" ", "p_name", "p_type", "p_brand"))
    return _part(s, d).select("p_partkey", norm2(vec).alias("n2"), F.array_join(F.array_sort(F.transform(F.map_entries(vec), lambda e: F.concat_ws(":", F.lpad(e["key"].cast("string"), 3, "0"), e["value"].cast("string")))), ",").alias("vec"))


HASH_EMBEDDING_SQL = r"""with w as (select p_partkey, regexp_replace(regexp_replace(lower(u), '[0-9]+', '#', 'g'), '^[^a-z0-9#]+|[^a-z0-9#]+$', '', 'g') as w
  from (select p_partkey, unnest(string_split(p_name || ' ' || p_type || ' ' || p_brand, ' ')) as u from part) x),
b as (select p_partkey, cast(('0x' || substr(md5(w), 1, 7)) as bigint) % 256 as b, count(*) as n from w where w not in ('', 'a', 'of', 'the') group by 1, 2)
select p_partkey, cast(sum(n * n) as bigint) as n2, string_agg(lpad(cast(b as varchar), 3, '0') || ':' || cast(n as varchar), ',' order by lpad(cast(b as varchar), 3, '0')) as vec from b group by p_partkey"""


def tokens_by_document(s: SparkSession, d: str) -> DataFrame:
    return s.read.parquet(f"{d}/documents.parquet").select("doc_id", n_tokens(F.col("text")).alias("tokens"))


def full_scan_cost(s: SparkSession, d: str) -> DataFrame:
    """Tokens of the full-scan operators on documents: the whole text for each of three filters that is still needed."""
    docs = s.read.parquet(f"{d}/documents.parquet").select("doc_id", n_tokens(F.col("text")).cast("bigint").alias("t"), F.col("text").contains("licen").alias("a"), F.col("text").contains("@").alias("b"))
    return docs.groupBy(F.col("a").alias("first"), F.col("b").alias("second")).agg(F.count(F.lit(1)).alias("docs"), F.sum(F.col("t") + F.when(F.col("a"), F.col("t") + F.when(F.col("b"), F.col("t")).otherwise(0)).otherwise(0)).alias("tokens"))


def benchmark_hits(s: SparkSession, d: str) -> DataFrame:
    """Retrieval truth: which document holds which passage, word for word. Only documents that hold some five words inside a passage are held against it.

    The first and last word of a passage may be parts of longer ones in the text, so its second to sixth words are looked up; passages of fewer than
    seven words are few, or refused, and are held against every text.
    """
    docs, items = s.read.parquet(f"{d}/documents.parquet"), s.read.parquet(f"{d}/benchmark.parquet").withColumnRenamed("text", "passage")
    words = lambda c: F.regexp_extract_all(c, F.lit(r"\S+"), 0)
    keyed = items.select("item_id", "passage", words(F.col("passage")).alias("w"))
    runs = F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("w") - 4), lambda i: F.xxhash64(F.slice("w", i, 5))))
    shingled = docs.select("doc_id", "text", words(F.col("text")).alias("w")).where("size(w) >= 5").select("doc_id", "text", F.explode(runs).alias("run"))
    long = keyed.where("size(w) >= 7").select("item_id", "passage", F.xxhash64(F.slice("w", 2, 5)).alias("run"))
    found = shingled.join(long, "run").where(F.contains("text", F.col("passage"))).select("doc_id", "item_id")
    short = few(keyed.where("size(w) < 7").select("item_id", "passage"))
    return found.unionByName(docs.join(short, F.contains("text", F.col("passage"))).select("doc_id", "item_id"))


def sentence_rows(s: SparkSession, d: str) -> DataFrame:
    docs = s.read.parquet(f"{d}/conversations.parquet").select("conv_id", "turn", F.posexplode(sentences(F.col("text"))).alias("pos", "sentence"))
    return docs.select("conv_id", "turn", n_tokens(F.col("sentence")).alias("tokens")).groupBy("conv_id").agg(F.sum("tokens").alias("tokens"))


def _vectors(s: SparkSession, d: str) -> DataFrame:
    return s.read.parquet(f"{d}/embeddings.parquet")


def _asked(s: SparkSession, d: str) -> DataFrame:
    """The probes of all searches: every vector whose id is divisible by 20."""
    return _vectors(s, d).where("vec_id % 20 = 0").select(F.col("vec_id").alias("probe"), F.col("embedding").alias("pvec"))


def exact_topk(s: SparkSession, d: str) -> DataFrame:
    return ExactIndex(_vectors(s, d)).topk(_asked(s, d), 5).select("probe", "rank", "key")


def vector_range(s: SparkSession, d: str) -> DataFrame:
    return ExactIndex(_vectors(s, d)).range(_asked(s, d), 1.15).select("probe", "key", F.round("dist", 5).alias("dist"))


_DIST = "sqrt(list_sum(list_transform(list_zip(cast(v.embedding as double[]), cast(p.embedding as double[])), lambda z: (z[1] - z[2]) * (z[1] - z[2]))))"
TOPK_SQL = f"""select probe, cast(rank as integer) as rank, key from (select p.vec_id as probe, v.vec_id as key,
 row_number() over (partition by p.vec_id order by round({_DIST}, 9), v.vec_id) as rank from embeddings v, embeddings p where p.vec_id % 20 = 0) x where rank <= 5"""
RANGE_SQL = f"select p.vec_id as probe, v.vec_id as key, round({_DIST}, 5) as dist from embeddings v, embeddings p where p.vec_id % 20 = 0 and {_DIST} <= 1.15"


def _recall(found: DataFrame, s: SparkSession, d: str) -> DataFrame:
    truth = ExactIndex(_vectors(s, d)).topk(_asked(s, d), 10).select("probe", "key")
    return truth.join(found.select("probe", "key", F.lit(1).alias("hit")), ["probe", "key"], "left").agg(F.avg(F.coalesce("hit", F.lit(0)).cast("double")).alias("recall"), F.count(F.lit(1)).alias("n"))


def ivf_recall(s: SparkSession, d: str) -> DataFrame:
    return _recall(IVFIndex(_vectors(s, d), 16).topk(_asked(s, d), 10, 12), s, d)


def pq_recall(s: SparkSession, d: str) -> DataFrame:
    """A fifth of the vectors is ranked again exactly: vectors without clusters leave little in their codes."""
    vectors = _vectors(s, d)
    return _recall(PQIndex(vectors).topk(_asked(s, d), 10, math.ceil(vectors.count() / 5)), s, d)


def lsh_join(s: SparkSession, d: str) -> DataFrame:
    return LSHIndex(_vectors(s, d)).join(1.0)


def bucket_histogram(s: SparkSession, d: str) -> DataFrame:
    """Documents by the hash bucket of their source: the hash that vectors and samples are made with."""
    return s.read.parquet(f"{d}/documents.parquet").groupBy(bucket(F.col("source")).alias("bucket")).agg(F.count(F.lit(1)).alias("n"))


def tuple_prf1(s: SparkSession, d: str) -> DataFrame:
    """Precision, recall and F1 of a faulty answer, tuple by tuple, as multisets."""
    from docspj.metrics import scores

    c = s.read.parquet(f"{d}/customer.parquet")
    truth = c.where("c_acctbal >= 5000").select("c_mktsegment", "c_nationkey")
    got = c.where("c_acctbal >= 4000 and c_custkey % 7 <> 0").select("c_mktsegment", "c_nationkey")
    return scores(got, truth).select(*[F.round(x, 6).alias(x) for x in ("precision", "recall", "f1")])


PRF1_SQL = """with t as (select c_mktsegment, c_nationkey, count(*) as n from customer where c_acctbal >= 5000 group by 1, 2),
g as (select c_mktsegment, c_nationkey, count(*) as n from customer where c_acctbal >= 4000 and c_custkey % 7 <> 0 group by 1, 2),
m as (select cast(sum(least(t.n, g.n)) as double) as hit from t join g on t.c_mktsegment = g.c_mktsegment and t.c_nationkey = g.c_nationkey),
x as (select hit / (select sum(n) from g) as p, hit / (select sum(n) from t) as r from m)
select round(p, 6) as precision, round(r, 6) as recall, round(2 * p * r / (p + r), 6) as f1 from x"""


def hash_sample(s: SparkSession, d: str) -> DataFrame:
    """5 % of the documents, those of least seeded md5, as a threshold on the hash."""
    return s.read.parquet(f"{d}/documents.parquet").where(F.conv(F.substring(F.md5(F.concat(F.lit("sample:"), F.col("doc_id").cast("string"))), 1, 6), 16, 10).cast("bigint") < int(0.05 * 16**6)).select("doc_id")


def selectivity_all_leaves(s: SparkSession, d: str) -> DataFrame:
    """The share of parts that satisfies each leaf, in one pass."""
    return _part(s, d).agg(*[F.round(F.avg(F.expr(q).cast("int")), 6).alias(f"p{i}") for i, q in LEAF_SQL.items()])


def segment_order(s: SparkSession, d: str) -> DataFrame:
    """Context assembly: a conversation's turns in order, cut at 400 characters for the eye."""
    t = s.read.parquet(f"{d}/conversations.parquet")
    joined = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "role"))), lambda x: x["role"]), ",")
    return t.groupBy("conv_id").agg(joined.alias("roles"))


def running_tokens(s: SparkSession, d: str) -> DataFrame:
    t = s.read.parquet(f"{d}/conversations.parquet").select("conv_id", "turn", n_tokens(F.col("text")).cast("bigint").alias("tokens"))
    return t.withColumn("upto", F.sum("tokens").over(Window.partitionBy("conv_id").orderBy("turn").rowsBetween(Window.unboundedPreceding, 0)))


_TOKENS = r"len(regexp_extract_all({}, '\S+'))"


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "order_and_priority": best_cost(AND3), "order_or_priority": best_cost(OR3), "order_tree": best_cost(TREE4), "expected_cost_and": expected_written(AND3), "expected_cost_or": expected_written(OR3),
        "lazy_ledger_and": ledger(AND3), "lazy_ledger_or": ledger(OR3), "lazy_ledger_tree": ledger(TREE4), "order_arms_cost": arms, "argmin_order": argmin_order, "token_ledger": token_ledger, "join_plan_costs": join_costs, "join_in_filter": join_in_filter,
        "hash_embedding": hash_embedding, "document_tokens": tokens_by_document, "baseline_fullscan_cost": full_scan_cost, "benchmark_passage_hits": benchmark_hits, "sentence_rows": sentence_rows, "vector_exact_topk": exact_topk,
        "vector_range": vector_range, "vector_ivf_recall": ivf_recall, "vector_pq_recall": pq_recall, "vector_lsh_join": lsh_join, "hash_buckets": bucket_histogram, "tuple_prf1": tuple_prf1, "hash_sample": hash_sample,
        "selectivity_all_leaves": selectivity_all_leaves, "context_roles": segment_order, "running_tokens": running_tokens,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "order_and_priority": _enumerated_sql(AND3, "{}"), "order_or_priority": _enumerated_sql(OR3, "(1 - {})"), "order_tree": _tree_sql(), "expected_cost_and": _expected_written_sql(AND3, "{}"),
        "expected_cost_or": _expected_written_sql(OR3, "(1 - {})"), "lazy_ledger_and": _flat_ledger_sql("and"), "lazy_ledger_or": _flat_ledger_sql("or"), "order_arms_cost": _arms_sql(), "argmin_order": _argmin_sql(), "token_ledger": _token_ledger_sql(),
        "join_plan_costs": JOIN_COSTS_SQL, "join_in_filter": "select c_custkey, c_name from customer where c_nationkey in (select n_nationkey from nation where n_regionkey = 2)", "hash_embedding": HASH_EMBEDDING_SQL,
        "document_tokens": f"select doc_id, cast({_TOKENS.format('text')} as integer) as tokens from documents",
        "baseline_fullscan_cost": f"""select a as first, b as second, count(*) as docs, cast(sum(t + case when a then t + case when b then t else 0 end else 0 end) as bigint) as tokens
          from (select {_TOKENS.format('text')} as t, contains(text, 'licen') as a, contains(text, '@') as b from documents) x group by a, b""",
        "benchmark_passage_hits": "select doc_id, item_id from documents d, benchmark b where contains(d.text, b.text)",
        "sentence_rows": f"select conv_id, cast(sum({_TOKENS.format('text')}) as bigint) as tokens from conversations group by conv_id", "vector_exact_topk": TOPK_SQL, "vector_range": RANGE_SQL,
        "hash_buckets": "select cast(cast(('0x' || substr(md5(source), 1, 7)) as bigint) % 256 as integer) as bucket, count(*) as n from documents group by 1", "tuple_prf1": PRF1_SQL,
        "hash_sample": f"select doc_id from documents where cast(('0x' || substr(md5('sample:' || cast(doc_id as varchar)), 1, 6)) as bigint) < {int(0.05 * 16**6)}",
        "selectivity_all_leaves": "select " + ", ".join(f"round(avg(case when {q} then 1.0 else 0.0 end), 6) as p{i}" for i, q in LEAF_SQL.items()) + " from part",
        "context_roles": "select conv_id, string_agg(role, ',' order by turn) as roles from conversations group by conv_id",
        "running_tokens": f"select conv_id, turn, cast({_TOKENS.format('text')} as bigint) as tokens, cast(sum({_TOKENS.format('text')}) over (partition by conv_id order by turn rows unbounded preceding) as bigint) as upto from conversations",
    }
