"""Queries of the retrieval methods, the tree ledger and the joins' costs, with SQL that takes another way to the same answer.

Parts stand for documents and segments: a part's text is its name, type and brand.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from docspj.functions.text import STOP_WORDS, embed, n_tokens, norm2
from docspj.model import Leaf, all_of, attributes_of, ge, leaves, normalise
from docspj.operators.index import TwoLevelIndex, kmeans_centres
from docspj.operators.lazy import fold_executor, planned
from docspj.operators.retrieval import Probes, Thresholds, description, doc_distance, fit_gamma, fit_tau, hashed, mean_embedding, near_segments, query_embedding, retrieve_docs, sample_docs
from docspj.operators.segments import segment, summarise
from docspj.plans.ordering import plan_node
from docspj.registry.methods import COST, P, TREE4, cost_sql, LEAF_SQL
from docspj.sources.corpora import raw_documents, spec

PART = spec("part")
ATTRIBUTES = [PART[n] for n in ("type", "size", "price")]
TAU, GAMMA, MARGIN = 1.23, 1.2, 0.1
#: Two texts that stand for evidence of a part.
EVIDENCE = ("Part 17 SMALL Brand#3", "Part 5 PROMO Brand#11")
_TEXT_SQL = "p_name || ' ' || p_type || ' ' || p_brand"
_WORDS_SQL = r"regexp_replace(regexp_replace(u, '[0-9]+', '#', 'g'), '^[^\p{L}\p{N}#]+|[^\p{L}\p{N}#]+$', '', 'g')"
_CUT_SQL = r"string_split_regex(regexp_replace(text, '([.!?])[\t\n\x0B\f\r ]+', '\1' || chr(10), 'g'), '\n+')"


def vectors_sql(name: str, source: str) -> str:
    """Common table expressions <name>_b(id, b, n) and <name>_n(id, n2) of the hashed vectors of source, a select of id and text."""
    stop = ", ".join(f"'{w}'" for w in STOP_WORDS)
    return rf"""{name}_w as (select id, {_WORDS_SQL} as w from (select id, unnest(regexp_extract_all(lower(text), '[^\t\n\x0B\f\r ]+')) as u from ({source}) s) x),
{name}_b as (select id, cast(('0x' || substr(md5(w), 1, 7)) as bigint) % 256 as b, count(*) as n from {name}_w where w <> '' and w not in ({stop}) group by 1, 2),
{name}_n as (select id, cast(sum(n * n) as double) as n2 from {name}_b group by id)"""


def _literal_texts(texts: list[str]) -> str:
    return " union all ".join("select {} as id, '{}' as text".format(i, t.replace("'", "''")) for i, t in enumerate(texts))


def _query_sql() -> str:
    """q(b, x): the mean of the attributes' normalised vectors; qq: its squared length."""
    return f"""{vectors_sql('a', _literal_texts([description(a) for a in ATTRIBUTES]))},
q as (select b, sum(n / sqrt(n2)) / {len(ATTRIBUTES)} as x from a_b join a_n using (id) group by b), qq as (select sum(x * x) as x2 from q)"""


def _doc_distances_sql() -> str:
    return f"""{_query_sql()}, {vectors_sql('d', f'select p_partkey as id, {_TEXT_SQL} as text from part')},
dist as (select id, sqrt(greatest(0, 1 + (select x2 from qq) - 2 * coalesce(sum(n * x), 0) / sqrt(max(n2)))) as dist from d_b join d_n using (id) left join q using (b) group by id)"""


def _parts(s: SparkSession, d: str) -> DataFrame:
    vec = embed(F.concat_ws(" ", "p_name", "p_type", "p_brand"))
    rows = s.read.parquet(f"{d}/part.parquet").select(F.lit("part").alias("corpus"), F.col("p_partkey").alias("doc_key"), "p_type", F.concat_ws(" ", "p_name", "p_type", "p_brand").alias("text"), vec.alias("vec"))
    return rows.withColumns({"n2": norm2(F.col("vec")), "seg_no": F.lit(0), "n_tokens": n_tokens(F.col("text"))}).withColumns({"vecs": F.array("vec"), "n2s": F.array("n2")})


def _index(s: SparkSession, d: str) -> TwoLevelIndex:
    rows = _parts(s, d)
    return TwoLevelIndex(rows.select("corpus", "doc_key", "p_type", "vecs", "n2s"), rows.select("corpus", "doc_key", "seg_no", "text", "n_tokens", "vec", "n2"))


def query_vector(s: SparkSession, d: str) -> DataFrame:
    """The non-zero places of the embedding of a query by example, for the parts of each type: the mean of its parts' vectors."""
    return mean_embedding(_parts(s, d), "p_type").select("p_type", "bucket", F.round("value", 6).alias("value"))


def _query_vector_sql() -> str:
    return f"""with {vectors_sql('d', f'select p_partkey as id, {_TEXT_SQL} as text from part')}, c as (select p_type, count(*) as m from part join d_n on id = p_partkey group by p_type)
select part.p_type, cast(b as integer) as bucket, round(sum(n / sqrt(n2)) / max(m), 6) as value
from d_b join d_n using (id) join part on p_partkey = id join c on c.p_type is not distinct from part.p_type group by part.p_type, b"""


def doc_filter(s: SparkSession, d: str) -> DataFrame:
    """Documents within a radius of the query."""
    return retrieve_docs(_index(s, d).docs, query_embedding(ATTRIBUTES), TAU).select(F.col("doc_key").alias("p_partkey"), F.round("doc_dist", 6).alias("dist"))


def _sampled(s: SparkSession, d: str) -> DataFrame:
    return sample_docs(_index(s, d).docs, 0.05, "sample", 0)


_SAMPLE_SQL = "cast(('0x' || substr(md5('sample:' || cast(p_partkey as varchar)), 1, 12)) as bigint) < 0.05 * 281474976710656"


def tau(s: SparkSession, d: str) -> DataFrame:
    """The radius that the relevant documents of a sample give; parts of one type are the relevant ones."""
    relevant = _sampled(s, d).where("p_type = 'SMALL'").agg(F.max(doc_distance(query_embedding(ATTRIBUTES)))).first()[0]
    return s.createDataFrame([(round(fit_tau([] if relevant is None else [relevant], MARGIN), 6),)], "tau double")


def _tau_sql() -> str:
    return f"""with {_doc_distances_sql()} select round(least(1.45, coalesce(max(dist) + {MARGIN}, 1.45)), 6) as tau
from dist join part on p_partkey = id where p_type = 'SMALL' and {_SAMPLE_SQL}"""


def gamma(s: SparkSession, d: str) -> DataFrame:
    """The radius that the evidence of a sample gives: its diameter, and a margin. Distinct vectors alone go to the driver."""
    rows = _sampled(s, d).select(F.array_sort(F.map_entries(F.col("vecs")[0])).alias("e")).distinct().collect()
    vectors = [_unit({e["key"]: e["value"] for e in r.e}) for r in rows]
    return s.createDataFrame([(round(fit_gamma(vectors, MARGIN), 5),)], "gamma double")


def _unit(counts: dict[int, int]) -> list[float]:
    from docspj.functions.text import unit

    return unit(counts)


def _gamma_sql() -> str:
    vectors = vectors_sql("d", f"select p_partkey as id, {_TEXT_SQL} as text from part where {_SAMPLE_SQL}")
    return f"""with {vectors}, pairs as (select x.id, y.id as other, 2 - 2 * sum(case when x.b = y.b then x.n * y.n else 0 end) / sqrt(max(xn.n2) * max(yn.n2)) as sq
from d_b x join d_n xn on xn.id = x.id, d_b y join d_n yn on yn.id = y.id group by 1, 2)
select round(sqrt(greatest(0, max(sq))) + {MARGIN}, 5) as gamma from pairs"""


def near(s: SparkSession, d: str) -> DataFrame:
    """Segments within the radius of a centre, among the documents within theirs."""
    index, a = _index(s, d), PART["type"]
    probes = Probes(query_embedding(ATTRIBUTES), {"type": [hashed(t) for t in EVIDENCE]}, Thresholds(TAU, {"type": GAMMA}))
    return near_segments(index, [a], probes, retrieve_docs(index.docs, probes.query, TAU)).select(F.col("doc_key").alias("p_partkey"), "n_tokens")


def _near_sql() -> str:
    return f"""with {_doc_distances_sql()}, {vectors_sql('e', _literal_texts(list(EVIDENCE)))},
hit as (select x.id, y.id as centre, sqrt(greatest(0, 2 - 2 * sum(case when x.b = y.b then x.n * y.n else 0 end) / sqrt(max(xn.n2) * max(yn.n2)))) as dist
from d_b x join d_n xn on xn.id = x.id, e_b y join e_n yn on yn.id = y.id group by 1, 2)
select p_partkey, cast(len(regexp_extract_all({_TEXT_SQL}, '[^ ]+')) as integer) as n_tokens from part where p_partkey in (select id from hit where dist <= {GAMMA}) and p_partkey in (select id from dist where dist <= {TAU})"""


def centres(s: SparkSession, d: str) -> DataFrame:
    """The centres of the vectors of a sample's parts, by type: (type, centre, bucket, value)."""
    rows = _sampled(s, d).select("p_type", F.array_sort(F.map_entries(F.col("vecs")[0])).alias("e")).groupBy("p_type", "e").count().orderBy("p_type", "e").collect()
    found = []
    for t in sorted({r.p_type for r in rows}):
        own = [r for r in rows if r.p_type == t]
        made = kmeans_centres([_unit({e["key"]: e["value"] for e in r.e}) for r in own], 3, counts=[r["count"] for r in own])
        found += [(t, k, i, round(x, 9)) for k, c in enumerate(made) for i, x in enumerate(c) if x]
    return s.createDataFrame(found, "type string, centre int, bucket int, value double")


def plain_cost(s: SparkSession, d: str) -> DataFrame:
    """Tokens that retrieval by description alone gives the reader, by attribute."""
    rows, parts = None, _parts(s, d)
    for a in ATTRIBUTES:
        probes = Probes([], {a.name: [hashed(description(a))]}, Thresholds(float("inf"), {a.name: GAMMA}))
        index = TwoLevelIndex(parts.select("corpus", "doc_key", "vecs", "n2s"), parts.select("corpus", "doc_key", "seg_no", "text", "n_tokens", "vec", "n2"))
        one = near_segments(index, [a], probes).agg(F.coalesce(F.sum("n_tokens"), F.lit(0)).cast("bigint").alias("tokens")).select(F.lit(a.name).alias("attr"), "tokens")
        rows = one if rows is None else rows.unionByName(one)
    return rows


def _plain_cost_sql() -> str:
    names = " ".join(f"when {i} then '{a.name}'" for i, a in enumerate(ATTRIBUTES))
    return f"""with {vectors_sql('a', _literal_texts([description(a) for a in ATTRIBUTES]))}, {vectors_sql('d', f'select p_partkey as id, {_TEXT_SQL} as text from part')},
hit as (select x.id, y.id as a, sqrt(greatest(0, 2 - 2 * sum(case when x.b = y.b then x.n * y.n else 0 end) / sqrt(max(xn.n2) * max(yn.n2)))) as dist
from d_b x join d_n xn on xn.id = x.id, a_b y join a_n yn on yn.id = y.id group by 1, 2)
select case a {names} end as attr, cast(sum(case when dist <= {GAMMA} then len(regexp_extract_all({_TEXT_SQL}, '[^ ]+')) else 0 end) as bigint) as tokens from hit join part on p_partkey = id group by a"""


def summaries(s: SparkSession, d: str) -> DataFrame:
    """Each document's opening sentence."""
    rows = raw_documents(s, d).where("text is not null")
    return summarise(rows, "lead").select(F.substring("doc_key", 5, 30).cast("bigint").alias("doc_id"), "summary")


_SUMMARIES_SQL = f"select doc_id, coalesce(list_filter(list_transform({_CUT_SQL}, lambda x: trim(x)), lambda x: x <> '')[1], '') as summary from documents where text is not null"


def semantic_segments(s: SparkSession, d: str) -> DataFrame:
    """Conversations' turns cut where neighbouring sentences are less alike: (conv_id, turn, segment, first and last sentence)."""
    rows = s.read.parquet(f"{d}/conversations.parquet").select(F.lit("talk").alias("corpus"), F.concat_ws(":", "conv_id", "turn").alias("doc_key"), "text")
    made = segment(rows, max_tokens=10**9)
    key = F.split("doc_key", ":")
    return made.select(key[0].cast("bigint").alias("conv_id"), key[1].cast("bigint").alias("turn"), "seg_no", "first_sent", "last_sent")


def _segments_sql() -> str:
    """Sentences as rows, cosines by joins of buckets, cuts by windows."""
    split = f"select conv_id, turn, list_filter(list_transform({_CUT_SQL}, lambda x: trim(x)), lambda x: x <> '') as s from conversations"
    return f"""with sents as materialized (select row_number() over () as id, conv_id, turn, pos - 1 as pos, s[pos] as text from (select *, unnest(range(1, len(s) + 1)) as pos from ({split}) t) x),
{vectors_sql('v', 'select id, text from sents')},
seq as (select id, lag(id) over (partition by conv_id, turn order by pos) as before, conv_id, turn, pos from sents),
dots as (select seq.id, sum(x.n * y.n) as dot from seq join v_b x on x.id = seq.id join v_b y on y.id = seq.before and y.b = x.b group by 1),
cuts as (select conv_id, turn, pos, case when pos = 0 then 0 when sqrt(greatest(0.0, 2 - 2 * case when a.n2 > 0 and b.n2 > 0 then coalesce(dot, 0) / sqrt(a.n2 * b.n2) else 0 end)) > {(2 - 2 * 0.25) ** 0.5!r} then 1 else 0 end as cut
from seq left join dots using (id) left join v_n a on a.id = seq.id left join v_n b on b.id = seq.before),
segs as (select conv_id, turn, pos, sum(cut) over (partition by conv_id, turn order by pos) as seg_no from cuts)
select conv_id, turn, cast(seg_no as integer) as seg_no, cast(min(pos) as integer) as first_sent, cast(max(pos) as integer) as last_sent from segs group by 1, 2, 3"""


def tree_ledger_sql() -> str:
    """Four leaves in two disjunctions: ranks by cases, and the walk of each document by cases over its truths."""
    name = {x.id: x.attr for x in leaves(TREE4)}
    leaf = lambda i: f"{cost_sql(name[i])} as c{i}, cast({P[i]} as double) as p{i}, {LEAF_SQL[i]} as t{i}"
    first = lambda a, b: f"p{a} / c{a} >= p{b} / c{b}"
    pair = lambda x, a, b: f"""case when {first(a, b)} then c{a} else c{b} end as x{x}, case when {first(a, b)} then t{a} else t{b} end as u{x}, case when {first(a, b)} then c{b} else c{a} end as y{x},
case when {first(a, b)} then c{a} + (1 - p{a}) * c{b} else c{b} + (1 - p{b}) * c{a} end as e{x}, 1 - (1 - p{a}) * (1 - p{b}) as q{x}, t{a} or t{b} as o{x}"""  # noqa: E731
    walk = lambda x: f"x{x} + case when u{x} then 0 else y{x} end"
    calls = lambda x: f"1 + case when u{x} then 0 else 1 end"
    ordered = lambda f: f"case when (1 - q1) / e1 >= (1 - q2) / e2 then {f(1)} + case when o1 then {f(2)} else 0 end else {f(2)} + case when o2 then {f(1)} else 0 end end"
    return f"""with l as (select p_partkey, {', '.join(leaf(i) for i in (1, 2, 3, 4))} from part), g as (select p_partkey, {pair(1, 1, 2)}, {pair(2, 3, 4)} from l)
select p_partkey, o1 and o2 as kept, cast({ordered(walk)} as bigint) as tokens, cast({ordered(calls)} as integer) as calls from g"""


#: Costs of reading an attribute of a customer or nation, and chances as a sample would give them.
SIDES = {
    "customer": (normalise(all_of(ge("balance", 5000), Leaf("segment", "=", ("BUILDING",)))), {1: 0.5, 2: 0.2}, {"balance": "c_custkey * 7 % 40 + 10", "segment": "c_custkey * 11 % 60 + 5", "key": "c_custkey * 3 % 30 + 8"}),
    "nation": (normalise(Leaf("region", "=", (2,))), {1: 0.2}, {"region": "n_nationkey * 5 % 20 + 30", "key": "n_nationkey % 10 + 15"}),
}


def _side(s: SparkSession, d: str, t: str) -> tuple[DataFrame, dict[str, Column]]:
    costs = SIDES[t][2]
    rows = s.read.parquet(f"{d}/{t}.parquet").selectExpr("*", *[f"cast({q} as bigint) as cost_{a}" for a, q in costs.items()])
    return rows, {a: F.col(f"cost_{a}") for a in costs}


def choose_side(s: SparkSession, d: str) -> DataFrame:
    """For each side the sum over its documents of what filters and then the key are expected to cost, and whether it goes first."""
    sums = []
    for t, (tree, p, _) in SIDES.items():
        rows, cost = _side(s, d, t)
        chance = p[1] * p.get(2, 1.0)
        total = F.sum(plan_node(tree, cost, p)["c"]) + chance * F.sum(cost["key"])
        sums.append(rows.agg(F.round(total, 4).alias("terms")).select(F.lit(t).alias("side"), "terms"))
    both = sums[0].unionByName(sums[1])
    least = both.agg(F.min("terms").alias("least"))
    return both.crossJoin(F.broadcast(least)).select("side", "terms", (F.col("terms") == F.col("least")).alias("goes_first"))


_CHOOSE_SIDE_SQL = """with c as (select c_custkey * 7 % 40 + 10 as a, c_custkey * 11 % 60 + 5 as b, c_custkey * 3 % 30 + 8 as k from customer), n as (select n_nationkey * 5 % 20 + 30 as a, n_nationkey % 10 + 15 as k from nation),
s as (select 'customer' as side, round(sum(cast(least(a + 0.5 * b, b + 0.2 * a) as double)) + 0.5 * 0.2 * sum(k), 4) as terms from c union all select 'nation', round(sum(a) + cast(0.2 as double) * sum(k), 4) from n)
select side, terms, terms = (select min(terms) from s) as goes_first from s"""


def adaptive_cost(s: SparkSession, d: str) -> DataFrame:
    """What a join with the nations first costs: their filter, their keys, and the customers' filters and membership filter in each document's order."""
    (n_tree, n_p, _), (c_tree, c_p, _) = SIDES["nation"], SIDES["customer"]
    nations, n_cost = _side(s, d, "nation")
    first = fold_executor(planned(nations, n_tree, n_cost, n_p), n_tree, {"region": F.col("n_regionkey")}, n_cost)
    members = first.where("kept").select(F.col("n_nationkey").alias("member")).distinct()
    customers, c_cost = _side(s, d, "customer")
    tree = normalise(all_of(Leaf("key", "in", ()), c_tree))
    p = {1: 0.2} | {i + 1: x for i, x in c_p.items()}
    rows = customers.join(members, F.col("c_nationkey") == F.col("member"), "left").withColumn("is_in", F.col("member").isNotNull())
    value = {"key": F.col("c_nationkey"), "balance": F.col("c_acctbal"), "segment": F.col("c_mktsegment")}
    second = fold_executor(planned(rows, tree, c_cost, p), tree, {a: value[a] for a in attributes_of(tree)}, c_cost, (), {1: F.col("is_in")})
    phase = lambda name, df, x, calls: df.agg(F.coalesce(F.sum(x), F.lit(0)).cast("bigint").alias("tokens"), F.coalesce(F.sum(calls), F.lit(0)).cast("bigint").alias("calls")).select(F.lit(name).alias("phase"), "tokens", "calls")
    return phase("filter", first, "tokens", "calls").unionByName(phase("key", first.where("kept"), "cost_key", F.lit(1))).unionByName(phase("join", second, "tokens", "calls"))


_ADAPTIVE_COST_SQL = """with n as (select n_nationkey, n_regionkey = 2 as ok, n_nationkey * 5 % 20 + 30 as f, n_nationkey % 10 + 15 as k from nation),
l as (select c_custkey, 1 as leaf, c_custkey * 3 % 30 + 8 as c, cast(0.2 as double) as p, case when c_nationkey in (select n_nationkey from n where ok) then 1 else 0 end as t from customer
 union all select c_custkey, 2, c_custkey * 7 % 40 + 10, cast(0.5 as double), case when c_acctbal >= 5000 then 1 else 0 end from customer
 union all select c_custkey, 3, c_custkey * 11 % 60 + 5, cast(0.2 as double), case when c_mktsegment = 'BUILDING' then 1 else 0 end from customer),
r as (select *, row_number() over (partition by c_custkey order by (1 - p) / c desc, leaf) as place from l),
w as (select *, coalesce(min(t) over (partition by c_custkey order by place rows between unbounded preceding and 1 preceding), 1) as reached from r)
select 'filter' as phase, cast(sum(f) as bigint) as tokens, count(*) as calls from n union all select 'key', cast(coalesce(sum(k), 0) as bigint), count(*) from n where ok
union all select 'join', cast(sum(c * reached) as bigint), cast(sum(reached) as bigint) from w"""


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "query_embedding": query_vector, "doc_filter_tau": doc_filter, "fit_tau": tau, "fit_gamma": gamma, "segment_retrieve": near, "evidence_centres": centres, "baseline_plain_retrieval_cost": plain_cost,
        "summary_sentences": summaries, "semantic_segments": semantic_segments, "join_choose_side": choose_side, "join_adaptive_cost": adaptive_cost,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "query_embedding": _query_vector_sql(),
        "doc_filter_tau": f"with {_doc_distances_sql()} select id as p_partkey, round(dist, 6) as dist from dist where dist <= {TAU}",
        "fit_tau": _tau_sql(), "fit_gamma": _gamma_sql(), "segment_retrieve": _near_sql(), "baseline_plain_retrieval_cost": _plain_cost_sql(), "summary_sentences": _SUMMARIES_SQL, "semantic_segments": _segments_sql(),
        "join_choose_side": _CHOOSE_SIDE_SQL, "join_adaptive_cost": _ADAPTIVE_COST_SQL, "lazy_ledger_tree": tree_ledger_sql(),
    }
