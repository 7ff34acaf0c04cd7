"""The relational operators that queries over extracted tuples need around them: DataFrame form and SQL form of each."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

Query = Callable[[SparkSession, str], DataFrame]
_made: dict[str, tuple[Query, str | None]] = {}


def _query(sql: str | None = None) -> Callable[[Query], Query]:
    def keep(f: Query) -> Query:
        _made[f.__name__] = (f, sql)
        return f

    return keep


def _t(s: SparkSession, d: str, name: str) -> DataFrame:
    return s.read.parquet(f"{d.rstrip('/')}/{name}.parquet")


@_query("select doc_id, n_chars from documents where lang = 'en' and n_chars > 500")
def scan_documents(s, d):
    return _t(s, d, "documents").where("lang = 'en' and n_chars > 500").select("doc_id", "n_chars")


@_query("select event_type, cast(sum(cast(json_extract_string(props, '$.k') as bigint)) as bigint) as total from events group by event_type")
def event_props(s, d):
    return _t(s, d, "events").groupBy("event_type").agg(F.sum(F.get_json_object("props", "$.k").cast("bigint")).alias("total"))


@_query("select page_id, regexp_extract(html, '<title>(.*?)</title>', 1) as title, len(regexp_extract_all(html, '<p>')) as paragraphs from pages")
def page_text_tokens(s, d):
    return _t(s, d, "pages").select("page_id", F.regexp_extract("html", "<title>(.*?)</title>", 1).alias("title"), F.regexp_count("html", F.lit("<p>")).cast("bigint").alias("paragraphs"))


@_query("select conv_id, count(*) as turns, string_agg(role || ':' || length(text), ' ' order by turn) as shape from conversations group by conv_id")
def conversation_documents(s, d):
    turns = F.array_sort(F.collect_list(F.struct("turn", F.concat_ws(":", "role", F.char_length("text").cast("string")).alias("x"))))
    return _t(s, d, "conversations").groupBy("conv_id").agg(F.count(F.lit(1)).alias("turns"), F.array_join(F.transform(turns, lambda t: t["x"]), " ").alias("shape"))


@_query("select page_id, try_cast(regexp_extract(url, '/([0-9]+)', 1) as bigint) as no, length(html) as n from pages")
def project_typed(s, d):
    return _t(s, d, "pages").select("page_id", F.nullif(F.regexp_extract("url", "/([0-9]+)", 1), F.lit("")).try_cast("bigint").alias("no"), F.char_length("html").cast("bigint").alias("n"))


@_query("select p_partkey from part where p_brand = 'Brand#4'")
def filter_eq(s, d):
    return _t(s, d, "part").where(F.col("p_brand") == "Brand#4").select("p_partkey")


@_query("select p_partkey from part where p_size >= 30 and p_retailprice < 950")
def filter_range(s, d):
    return _t(s, d, "part").where((F.col("p_size") >= 30) & (F.col("p_retailprice") < 950)).select("p_partkey")


@_query("select p_partkey from part where p_size between 10 and 20")
def filter_between(s, d):
    return _t(s, d, "part").where(F.col("p_size").between(10, 20)).select("p_partkey")


@_query("select p_partkey from part where (p_type = 'SMALL' or p_size > 45) and (p_brand = 'Brand#1' or p_retailprice > 940 and p_size < 48)")
def filter_tree(s, d):
    c = F.col
    return _t(s, d, "part").where(((c("p_type") == "SMALL") | (c("p_size") > 45)) & ((c("p_brand") == "Brand#1") | (c("p_retailprice") > 940) & (c("p_size") < 48))).select("p_partkey")


@_query("select c_custkey from customer where c_mktsegment in ('BUILDING', 'MACHINERY') and c_nationkey in (1, 5, 7)")
def filter_in(s, d):
    return _t(s, d, "customer").where(F.col("c_mktsegment").isin("BUILDING", "MACHINERY") & F.col("c_nationkey").isin(1, 5, 7)).select("c_custkey")


@_query("select n_name, count(s_suppkey) as suppliers, max(s_name) is null as missing from nation left join supplier on s_nationkey = n_nationkey group by n_name")
def missing_owner(s, d):
    j = _t(s, d, "nation").join(_t(s, d, "supplier"), F.col("s_nationkey") == F.col("n_nationkey"), "left")
    return j.groupBy("n_name").agg(F.count("s_suppkey").alias("suppliers"), F.max("s_name").isNull().alias("missing"))


@_query("select c_custkey, n_name from customer join nation on c_nationkey = n_nationkey")
def join_customer_nation(s, d):
    return _t(s, d, "customer").join(F.broadcast(_t(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name")


@_query("select o_orderpriority, count(*) as n, cast(sum(l_quantity) as bigint) as qty from orders join lineitem on o_orderkey = l_orderkey group by o_orderpriority")
def join_orders_lineitem(s, d):
    j = _t(s, d, "lineitem").hint("merge").join(_t(s, d, "orders"), F.col("o_orderkey") == F.col("l_orderkey"))
    return j.groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").cast("bigint").alias("qty"))


@_query("select o_orderstatus, count(*) as n from orders join customer on o_custkey = c_custkey where c_acctbal > 5000 group by o_orderstatus")
def join_shuffled_hash(s, d):
    j = _t(s, d, "orders").join(_t(s, d, "customer").where("c_acctbal > 5000").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey"))
    return j.groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


@_query("select r_name, n_name, count(distinct c_custkey) as customers, count(distinct s_suppkey) as suppliers from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey join supplier on s_nationkey = n_nationkey group by r_name, n_name")
def join_star_four(s, d):
    """A nation's customers and suppliers don't depend on each other, so each are counted by themselves, in nations that have both."""
    c, p = (_t(s, d, t).select(F.col(f"{t[0]}_nationkey").alias("at"), F.col(k).alias("own")).distinct() for t, k in (("customer", "c_custkey"), ("supplier", "s_suppkey")))
    n = _t(s, d, "nation").join(_t(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select("r_name", "n_name", F.col("n_nationkey").alias("at"))
    n = n.join(c, "at", "left_semi").join(p, "at", "left_semi")
    count = lambda t, name: n.join(t, "at").groupBy("r_name", "n_name").agg(F.count_distinct("own").alias(name))
    other = count(p, "suppliers").toDF("r", "n", "suppliers")
    return count(c, "customers").join(other, F.col("r_name").eqNullSafe(F.col("r")) & F.col("n_name").eqNullSafe(F.col("n"))).select("r_name", "n_name", "customers", "suppliers")


@_query("select n_name, s_name from (select * from nation where n_nationkey < 20) a full outer join (select * from supplier where s_suppkey > 30) b on s_nationkey = n_nationkey")
def outer_nation_supplier(s, d):
    a, b = _t(s, d, "nation").where("n_nationkey < 20"), _t(s, d, "supplier").where("s_suppkey > 30")
    return a.join(b, F.col("s_nationkey") == F.col("n_nationkey"), "full_outer").select("n_name", "s_name")


@_query("select c_custkey from customer where c_nationkey in (select n_nationkey from nation where n_regionkey = 1)")
def in_semijoin(s, d):
    return _t(s, d, "customer").join(_t(s, d, "nation").where("n_regionkey = 1"), F.col("c_nationkey") == F.col("n_nationkey"), "left_semi").select("c_custkey")


@_query("select doc_id from documents where doc_id not in (select doc_id from labels)")
def cache_misses(s, d):
    return _t(s, d, "documents").join(_t(s, d, "labels"), "doc_id", "left_anti").select("doc_id")


@_query("select a.p_partkey as low, b.p_partkey as high from part a join part b on a.p_size = b.p_size and a.p_partkey < b.p_partkey and abs(a.p_retailprice - b.p_retailprice) <= 0.5")
def band_join_part(s, d):
    a = _t(s, d, "part").select(F.col("p_partkey").alias("low"), F.col("p_size").alias("sa"), F.col("p_retailprice").alias("pa"), F.explode(F.array(*[F.floor(F.col("p_retailprice") / 0.5) + k for k in (-1, 0, 1)])).alias("cell"))
    b = _t(s, d, "part").select(F.col("p_partkey").alias("high"), F.col("p_size").alias("sb"), F.col("p_retailprice").alias("pb"), F.floor(F.col("p_retailprice") / 0.5).alias("cell"))
    near = (F.col("sa") == F.col("sb")) & (F.col("low") < F.col("high")) & (F.abs(F.col("pa") - F.col("pb")) <= 0.5)
    return a.join(b, "cell").where(near).select("low", "high")


@_query("select a.event_id as first, b.event_id as second from events a join events b on a.user_id = b.user_id and b.ts > a.ts and b.ts <= a.ts + interval 1 hour")
def interval_join_events(s, d):
    e = _t(s, d, "events").select("event_id", "user_id", F.col("ts").cast("timestamp").cast("double").alias("at")).withColumn("hour", F.floor(F.col("at") / 3600))
    a = e.select(F.col("event_id").alias("first"), "user_id", F.col("at").alias("t"), F.explode(F.array("hour", F.col("hour") + 1)).alias("hour"))
    j = a.join(e, ["user_id", "hour"]).where((F.col("at") > F.col("t")) & (F.col("at") <= F.col("t") + 3600))
    return j.select("first", F.col("event_id").alias("second"))


@_query("select a.event_id, (select b.event_id from events b where b.user_id = a.user_id and b.event_type = 'purchase' and b.ts <= a.ts order by b.ts desc, b.event_id desc limit 1) as latest from events a where a.event_type <> 'purchase'")
def asof_events(s, d):
    e = _t(s, d, "events")
    w = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "purchase", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    found = e.withColumn("latest", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), True).over(w))
    return found.where("event_type <> 'purchase'").select("event_id", "latest")


@_query("select p.vec_id as probe, count(*) as n from embeddings v, (select * from embeddings where vec_id < 3) p where v.label = p.label group by p.vec_id")
def probe_cross(s, d):
    v = _t(s, d, "embeddings")
    p = v.where("vec_id < 3").select(F.col("vec_id").alias("probe"), F.col("label").alias("own"))
    return v.crossJoin(F.broadcast(p)).where("label = own").groupBy("probe").agg(F.count(F.lit(1)).alias("n"))


@_query("select lang, source, count(*) as n, cast(sum(n_chars) as bigint) as chars, round(avg(n_chars), 6) as mean from documents group by lang, source")
def ledger_by_attr(s, d):
    return _t(s, d, "documents").groupBy("lang", "source").agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"), F.round(F.avg("n_chars"), 6).alias("mean"))


@_query("select distinct c_nationkey, c_mktsegment from customer")
def distinct_keys(s, d):
    return _t(s, d, "customer").select("c_nationkey", "c_mktsegment").distinct()


@_query("select event_type, user_id % 3 as shard, count(*) as n from events group by grouping sets ((event_type, user_id % 3), (event_type), ())")
def ledger_grouping_sets(s, d):
    e = _t(s, d, "events").withColumn("shard", F.col("user_id") % 3)
    return e.groupingSets([["event_type", "shard"], ["event_type"], []], "event_type", "shard").agg(F.count(F.lit(1)).alias("n"))


@_query("select o_orderstatus, o_orderpriority, count(*) as n, round(sum(o_totalprice), 2) as total from orders group by rollup (o_orderstatus, o_orderpriority)")
def ledger_rollup(s, d):
    return _t(s, d, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@_query("select o_orderstatus, o_orderpriority, count(*) as n from orders group by cube (o_orderstatus, o_orderpriority)")
def ledger_cube(s, d):
    return _t(s, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


@_query("select user_id, count(*) filter (event_type = 'click') as click, count(*) filter (event_type = 'view') as view from events group by user_id")
def cost_pivot(s, d):
    p = _t(s, d, "events").groupBy("user_id").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1)))
    return p.select("user_id", F.coalesce("click", F.lit(0)).alias("click"), F.coalesce("view", F.lit(0)).alias("view"))


@_query("select p_partkey, 'size' as name, cast(p_size as double) as value from part union all select p_partkey, 'price', p_retailprice from part")
def cost_unpivot(s, d):
    p = _t(s, d, "part").select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price"))
    return p.unpivot("p_partkey", ["size", "price"], "name", "value")


@_query("select p_partkey, row_number() over w as rn, rank() over (partition by p_brand order by p_size) as rk, dense_rank() over (partition by p_brand order by p_size) as dr, ntile(4) over w as quarter from part window w as (partition by p_brand order by p_size, p_partkey)")
def rank_parts(s, d):
    w, v = Window.partitionBy("p_brand").orderBy("p_size", "p_partkey"), Window.partitionBy("p_brand").orderBy("p_size")
    return _t(s, d, "part").select("p_partkey", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.ntile(4).over(w).alias("quarter"))


@_query("select conv_id, turn, lag(role) over w as before, lead(role) over w as after, first_value(role) over w as first from conversations window w as (partition by conv_id order by turn)")
def neighbour_turns(s, d):
    w = Window.partitionBy("conv_id").orderBy("turn")
    return _t(s, d, "conversations").select("conv_id", "turn", F.lag("role").over(w).alias("before"), F.lead("role").over(w).alias("after"), F.first("role").over(w).alias("first"))


@_query("select event_id, round(sum(value) over (partition by user_id order by epoch(ts) range between 3600 preceding and current row), 4) as spend from events")
def range_frame_events(s, d):
    e = _t(s, d, "events").withColumn("at", F.col("ts").cast("timestamp").cast("double"))
    return e.select("event_id", F.round(F.sum("value").over(Window.partitionBy("user_id").orderBy("at").rangeBetween(-3600, 0)), 4).alias("spend"))


@_query("select p_partkey, p_retailprice from part order by p_retailprice desc, p_partkey limit 10")
def topk_parts(s, d):
    return _t(s, d, "part").select("p_partkey", "p_retailprice").orderBy(F.desc("p_retailprice"), "p_partkey").limit(10)


@_query("select p_partkey from part order by p_partkey limit 15 offset 30")
def page_of_parts(s, d):
    return _t(s, d, "part").select("p_partkey").orderBy("p_partkey").offset(30).limit(15)


@_query("select distinct doc_id from (select doc_id from documents where lang = 'fr' union all select doc_id from documents where n_chars < 300) x")
def union_segments(s, d):
    t = _t(s, d, "documents")
    return t.where("lang = 'fr'").select("doc_id").unionByName(t.where("n_chars < 300").select("doc_id")).distinct()


@_query("select c_nationkey from customer where c_acctbal > 5000 intersect all select s_nationkey from supplier")
def tuple_intersection(s, d):
    return _t(s, d, "customer").where("c_acctbal > 5000").select("c_nationkey").intersectAll(_t(s, d, "supplier").select("s_nationkey"))


@_query("select c_nationkey, c_mktsegment from customer where c_acctbal > 4000 except all select c_nationkey, c_mktsegment from customer where c_acctbal > 6000")
def tuple_errors(s, d):
    t = _t(s, d, "customer")
    return t.where("c_acctbal > 4000").select("c_nationkey", "c_mktsegment").exceptAll(t.where("c_acctbal > 6000").select("c_nationkey", "c_mktsegment"))


@_query("select page_id, split_part(url, '/', 3) as host, lower(split_part(url, ':', 1)) as scheme, contains(url, '?') as asks, length(url) as n from pages")
def page_url_parts(s, d):
    return _t(s, d, "pages").select("page_id", F.split_part("url", F.lit("/"), F.lit(3)).alias("host"), F.lower(F.split_part("url", F.lit(":"), F.lit(1))).alias("scheme"), F.col("url").contains("?").alias("asks"), F.char_length("url").cast("bigint").alias("n"))


@_query("select p_partkey, upper(p_type) as u, substr(p_brand, 7) as b, replace(p_name, ' ', '_') as r, lpad(cast(p_size as varchar), 4, '0') as l, levenshtein(p_type, 'SMELL') as e, trim('  ' || p_type || ' ') as t, reverse(p_type) as v from part")
def string_suite(s, d):
    return _t(s, d, "part").select("p_partkey", F.upper("p_type").alias("u"), F.substring("p_brand", 7, 100).alias("b"), F.replace("p_name", F.lit(" "), F.lit("_")).alias("r"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("l"), F.levenshtein("p_type", F.lit("SMELL")).cast("bigint").alias("e"), F.trim(F.concat(F.lit("  "), "p_type", F.lit(" "))).alias("t"), F.reverse("p_type").alias("v"))


@_query("select o_orderkey, year(o_orderdate) as y, month(o_orderdate) as m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') as first, date_diff('day', date '1992-01-01', cast(o_orderdate as date)) as days, strftime(o_orderdate + interval 30 day, '%Y-%m-%d') as due from orders")
def date_suite(s, d):
    o = F.col("o_orderdate")
    return _t(s, d, "orders").select("o_orderkey", F.year(o).cast("bigint").alias("y"), F.month(o).cast("bigint").alias("m"), F.date_format(F.date_trunc("month", o), "yyyy-MM-dd").alias("first"), F.datediff(F.to_date(o), F.lit("1992-01-01").cast("date")).cast("bigint").alias("days"), F.date_format(F.date_add(F.to_date(o), 30), "yyyy-MM-dd").alias("due"))


@_query("select p_partkey, round(sqrt(p_size), 6) as a, round(pow(p_size, 1.5), 6) as b, round(ln(p_retailprice), 6) as c, greatest(p_size, 20) as g, least(p_size, 20) as l, case when p_size = 7 then null else round(p_retailprice / (p_size - 7), 6) end as q from part")
def math_suite(s, d):
    return _t(s, d, "part").select("p_partkey", F.round(F.sqrt("p_size"), 6).alias("a"), F.round(F.pow("p_size", F.lit(1.5)), 6).alias("b"), F.round(F.ln("p_retailprice"), 6).alias("c"), F.greatest("p_size", F.lit(20)).alias("g"), F.least("p_size", F.lit(20)).alias("l"), F.round(F.try_divide("p_retailprice", F.col("p_size") - 7), 6).alias("q"))


@_query("select vec_id, round(list_sum(list_transform(embedding, lambda x: cast(x as double) * cast(x as double))), 5) as n2, len(list_filter(embedding, lambda x: x > 0)) as pos, list_max(embedding) > 0.3 as big from embeddings")
def array_suite(s, d):
    e = F.transform("embedding", lambda x: x.cast("double"))
    return _t(s, d, "embeddings").select("vec_id", F.round(F.aggregate(F.transform(e, lambda x: x * x), F.lit(0.0), lambda a, x: a + x), 5).alias("n2"), F.size(F.filter(e, lambda x: x > 0)).cast("bigint").alias("pos"), F.exists(F.col("embedding"), lambda x: x > F.lit(0.3).cast("float")).alias("big"))


@_query("select p_partkey, case when p_size > 25 then p_size else 0 end + case when p_retailprice > 25 then cast(floor(p_retailprice) as bigint) else 0 end as total, p_size as size from part")
def map_suite(s, d):
    m = F.map_from_entries(F.array(F.struct(F.lit("size"), F.col("p_size").cast("bigint")), F.struct(F.lit("price"), F.floor("p_retailprice").cast("bigint"))))
    kept = F.map_filter(m, lambda k, v: v > 25)
    return _t(s, d, "part").select("p_partkey", F.aggregate(F.map_values(kept), F.lit(0).cast("bigint"), lambda a, v: a + v).alias("total"), F.element_at(m, F.lit("size")).cast("int").alias("size"))


@_query("select p_partkey, name, value from (select p_partkey, 'size' as name, p_size as value from part union all select p_partkey, 'len', length(p_name) from part) x where value > 10")
def plan_array(s, d):
    entries = F.array(F.struct(F.lit("size").alias("name"), F.col("p_size").alias("value")), F.struct(F.lit("len").alias("name"), F.char_length("p_name").alias("value")))
    return _t(s, d, "part").select("p_partkey", F.inline(F.filter(entries, lambda e: e["value"] > 10)))


@_query("select c_custkey, c_acctbal from customer c where c_acctbal > (select avg(c_acctbal) from customer x where x.c_nationkey = c.c_nationkey) and exists (select 1 from nation n where n.n_nationkey = c.c_nationkey and n.n_regionkey = 3)")
def sql_subquery(s, d):
    _t(s, d, "customer").createOrReplaceTempView("docspj_customer")
    _t(s, d, "nation").createOrReplaceTempView("docspj_nation")
    return s.sql("with means as (select c_nationkey as k, avg(c_acctbal) as m from docspj_customer group by c_nationkey) select c_custkey, c_acctbal from docspj_customer join means on k = c_nationkey where c_acctbal > m and c_nationkey in (select n_nationkey from docspj_nation where n_regionkey = 3)")


@_query("select event_type, count(*) filter (value > 50) as high, round(avg(case when value > 50 then 1.0 else 0.0 end), 6) as share, min(value) as low from events group by event_type")
def conditional_aggregates(s, d):
    return _t(s, d, "events").groupBy("event_type").agg(F.count_if(F.col("value") > 50).alias("high"), F.round(F.avg(F.when(F.col("value") > 50, 1.0).otherwise(0.0)), 6).alias("share"), F.min("value").alias("low"))


@_query("select p_brand, arg_max(p_partkey, p_retailprice * 100000 + p_partkey) as dearest from part group by p_brand")
def dearest_part(s, d):
    return _t(s, d, "part").groupBy("p_brand").agg(F.max_by("p_partkey", F.col("p_retailprice") * 100000 + F.col("p_partkey")).alias("dearest"))


@_query()
def approximate_counts(s, d):
    return _t(s, d, "events").agg(F.approx_count_distinct("user_id").alias("users"), F.percentile_approx("value", 0.5).alias("median"))


def queries() -> dict[str, Query]:
    return {n: f for n, (f, _) in _made.items()}


def oracle_sql() -> dict[str, str]:
    return {n: sql for n, (_, sql) in _made.items() if sql}
