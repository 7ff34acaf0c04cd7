"""Three document suites over the given tables, with the truth each document was made from.

P: profiles of customers, nations, regions, suppliers and parts in one corpus. G: web pages. C: dossiers of orders. Every suite is
documents(corpus, doc_key, domain, text); `domain` and the truth are for measuring and never read by the engine.
"""

from __future__ import annotations

import re
from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from docspj.functions.text import n_tokens, sentences
from docspj.model import Attribute, TableSpec

REGIMES = ("pattern", "named", "disjoint")
_FRAMES = ("The {k} stands at {v}{u}.", "On record, the {k} is {v}{u}.", "By now the {k} amounts to {v}{u}.", "Files list a {k} of {v}{u}.")
_VALUES = {"string": r"([^.]+?)", "double": r"(-?[0-9]+(?:\.[0-9]+)?)", "bigint": r"(-?[0-9]+)", "date": r"([0-9]{4}-[0-9]{2}-[0-9]{2})", "boolean": r"(true|false)"}
#: attribute: type, unit, the phrase of the pattern regime, and three more phrases without a word in common.
_FACTS: dict[str, dict[str, tuple[str, str, tuple[str, str, str, str]]]] = {
    "customer": {
        "nation_name": ("string", "", ("home nation", "country of residence", "native land", "place it dwells")),
        "balance": ("double", " dollars", ("account balance", "money held", "sum outstanding", "funds remaining")),
        "segment": ("string", "", ("market segment", "trade it follows", "line of business", "industry served")),
    },
    "nation": {
        "region_name": ("string", "", ("world region", "continent around it", "wider area", "part of the globe")),
        "owner_name": ("string", "", ("official owner", "proprietor", "controlling party", "who possesses it")),
        "n_customers": ("bigint", " people", ("customer count", "number of buyers", "clientele", "purchasers altogether")),
    },
    "region": {
        "n_nations": ("bigint", "", ("nation count", "number of countries", "states inside", "lands altogether")),
        "n_customers": ("bigint", " people", ("customer count", "number of buyers", "clientele", "purchasers altogether")),
        "n_suppliers": ("bigint", " firms", ("supplier count", "number of vendors", "sellers inside", "providers altogether")),
    },
    "supplier": {
        "nation_name": ("string", "", ("home nation", "country of residence", "native land", "place it dwells")),
        "balance": ("double", " dollars", ("account balance", "money held", "sum outstanding", "funds remaining")),
    },
    "part": {
        "brand": ("string", "", ("brand label", "maker mark", "trade name", "manufacturer tag")),
        "type": ("string", "", ("product type", "kind of good", "class", "category")),
        "size": ("bigint", " units", ("size measure", "extent", "dimension", "bulk")),
        "price": ("double", " dollars", ("retail price", "cost in shops", "amount charged", "value asked")),
    },
    "order": {
        "status": ("string", "", ("processing status", "state", "stage reached", "progress")),
        "priority": ("string", "", ("handling priority", "urgency", "rank in queue", "pressing level")),
        "order_date": ("date", "", ("placement date", "day of purchase", "when bought", "calendar entry")),
        "total_price": ("double", " dollars", ("total price", "overall amount", "full bill", "grand sum")),
        "customer_name": ("string", "", ("ordering customer", "buyer", "purchaser", "client")),
        "n_lines": ("bigint", " entries", ("line count", "number of items", "rows inside", "positions altogether")),
        "total_qty": ("bigint", " pieces", ("quantity total", "pieces overall", "units together", "goods counted")),
        "last_ship_date": ("date", "", ("final shipping date", "latest dispatch", "last departure", "end of delivery")),
        "any_returned": ("boolean", "", ("return flag", "goods sent back", "reversal seen", "refund noted")),
    },
}
_ROOT = {"order": "order_key"}


def _phrase(table: str, name: str, regime: str, k: int) -> str:
    phrases = _FACTS[table][name][2]
    if regime == "named":
        return f"{table} {name.replace('_', ' ')}"
    return f"{table} {phrases[k if regime == 'disjoint' else 0]}"


def spec(table: str, regime: str = "pattern") -> TableSpec:
    """The virtual table of a rendered suite; patterns accept whatever wording of the regime."""
    verbs = "(?:stands at|is|amounts to|of)"
    root = _ROOT.get(table, "name")
    found = [Attribute(root, f"{table} {root.replace('_', ' ')}: whose {table} profile this is", "bigint" if root == "order_key" else "string", rf"{table} profile of ([^.]+)\.")]
    for name, (dtype, unit, phrases) in _FACTS[table].items():
        said = "|".join(dict.fromkeys(_phrase(table, name, regime, k) for k in range(4)))
        description = f"{table} {name.replace('_', ' ')}: the {phrases[0]} of the {table}"
        found.append(Attribute(name, description, dtype, rf"(?:{said}) {verbs} {_VALUES[dtype]}{unit}\.(?:\s|$)"))
    return TableSpec(table, tuple(found))


#: Patterns of web pages; count: and has: ask for a number of matches, or for one.
PAGE = TableSpec(
    "page",
    tuple(
        Attribute(name, f"page {name.replace('_', ' ')}", dtype, pattern)
        for name, dtype, pattern in [
            ("scheme", "string", r"^(https?)://"),
            ("host", "string", r"^https?://([^/]+)"),
            ("site", "string", r"^https?://[^/]*?([a-z0-9-]+\.example\.[a-z]+|example\.[a-z]+)"),
            ("tld", "string", r"^https?://[^/]*\.([a-z]+)/"),
            ("path_lang", "string", r"^https?://[^/]+/([a-z]{2})/"),
            ("path_no", "bigint", r"^https?://[^/]+/[a-z]{2}/([0-9]+)"),
            ("has_query", "boolean", r"has:^https?://\S*\?"),
            ("utm_source", "string", r"^https?://\S*utm_source=([a-z]+)"),
            ("html_lang", "string", r'<html lang="([a-z]+)"'),
            ("title", "string", r"<title>(.*?)</title>"),
            ("h1", "string", r"<h1>(.*?)</h1>"),
            ("track_id", "bigint", r"track\(([0-9]+)\)"),
            ("ad_id", "bigint", r"<!-- ad ([0-9]+)"),
            ("nav_links", "bigint", r"count:<li>"),
            ("n_paragraphs", "bigint", r"count:<p>"),
            ("footer_site", "string", r"&copy; ([^<]+)"),
        ]
    ),
)


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def truth(spark: SparkSession, sf_dir: str, table: str, only: DataFrame | None = None) -> DataFrame:
    """doc_key and the true attribute values of each document of a virtual table, or of those in only(doc_key); of a page what its patterns find in all of it."""
    if only is not None and table != "order":
        return _of(truth(spark, sf_dir, table), only)
    if table == "page":
        from docspj.operators.retrieval import extract

        return pages(spark, sf_dir).select("doc_key", *[extract(F.col("text"), a).alias(a.name) for a in PAGE.attributes])
    t = {n: _table(spark, sf_dir, n) for n in ("customer", "nation", "region", "supplier")}
    nation = t["nation"].select(F.col("n_nationkey").alias("nk"), "n_name", "n_regionkey")
    if table == "customer":
        return t["customer"].join(F.broadcast(nation), F.col("c_nationkey") == F.col("nk"), "left").select(
            F.concat(F.lit("customer:"), "c_custkey").alias("doc_key"), F.col("c_name").alias("name"), F.col("n_name").alias("nation_name"), F.col("c_acctbal").alias("balance"), F.col("c_mktsegment").alias("segment")
        )
    if table == "supplier":
        return t["supplier"].join(F.broadcast(nation), F.col("s_nationkey") == F.col("nk"), "left").select(
            F.concat(F.lit("supplier:"), "s_suppkey").alias("doc_key"), F.col("s_name").alias("name"), F.col("n_name").alias("nation_name"), F.col("s_acctbal").alias("balance")
        )
    if table == "part":
        return _table(spark, sf_dir, "part").select(
            F.concat(F.lit("part:"), "p_partkey").alias("doc_key"), F.col("p_name").alias("name"), F.col("p_brand").alias("brand"), F.col("p_type").alias("type"), F.col("p_size").cast("bigint").alias("size"), F.col("p_retailprice").alias("price")
        )
    buyers = t["customer"].groupBy(F.col("c_nationkey").alias("nk")).agg(F.count(F.lit(1)).alias("n_customers"))
    sellers = t["supplier"].groupBy(F.col("s_nationkey").alias("nk")).agg(F.count(F.lit(1)).alias("n_suppliers"), F.min_by("s_name", "s_suppkey").alias("owner_name"))
    full = nation.join(buyers, "nk", "left").join(sellers, "nk", "left").fillna(0, ["n_customers", "n_suppliers"]).join(F.broadcast(t["region"]), F.col("n_regionkey") == F.col("r_regionkey"), "left")
    if table == "nation":
        return full.select(F.concat(F.lit("nation:"), "nk").alias("doc_key"), F.col("n_name").alias("name"), F.col("r_name").alias("region_name"), "owner_name", "n_customers")
    if table == "region":
        sums = full.groupBy("r_regionkey", F.col("r_name").alias("name")).agg(F.count(F.lit(1)).alias("n_nations"), F.sum("n_customers").alias("n_customers"), F.sum("n_suppliers").alias("n_suppliers"))
        return sums.select(F.concat(F.lit("region:"), "r_regionkey").alias("doc_key"), "name", "n_nations", "n_customers", "n_suppliers")
    if table == "order":
        orders, lines = _table(spark, sf_dir, "orders"), _table(spark, sf_dir, "lineitem")
        if only is not None:
            # Keys meet the tables before lines are summed, not after.
            chosen = only.select(F.substring("doc_key", 7, 30).cast("bigint").alias("chosen"))
            orders, lines = orders.join(chosen, F.col("o_orderkey") == F.col("chosen"), "left_semi"), lines.join(chosen, F.col("l_orderkey") == F.col("chosen"), "left_semi")
        lines = lines.groupBy("l_orderkey").agg(
            F.count(F.lit(1)).alias("n_lines"), F.sum("l_quantity").cast("bigint").alias("total_qty"), F.max("l_shipdate").alias("last"), F.max((F.col("l_returnflag") == "R").cast("int")).alias("back")
        )
        return orders.join(lines, F.col("o_orderkey") == F.col("l_orderkey"), "left").join(t["customer"].select("c_custkey", "c_name"), F.col("o_custkey") == F.col("c_custkey"), "left").select(
            F.concat(F.lit("order:"), "o_orderkey").alias("doc_key"), F.col("o_orderkey").alias("order_key"), F.col("o_orderstatus").alias("status"), F.col("o_orderpriority").alias("priority"), F.to_date("o_orderdate").alias("order_date"),
            F.col("o_totalprice").alias("total_price"), F.col("c_name").alias("customer_name"), F.coalesce("n_lines", F.lit(0)).alias("n_lines"), F.coalesce("total_qty", F.lit(0)).alias("total_qty"), F.to_date("last").alias("last_ship_date"), (F.coalesce("back", F.lit(0)) == 1).alias("any_returned"),
        )
    raise KeyError(table)


def _shown_value(table: str, name: str) -> Column:
    return F.col(name).cast("decimal(15,2)") if _FACTS[table][name][0] == "double" else F.col(name)


def _said(table: str, name: str, regime: str, kind: Column) -> Column:
    unit, value = _FACTS[table][name][1], _shown_value(table, name).cast("string")
    sentence = lambda k: F.concat(*[F.lit(x) if x != "\0" else value for x in _split(_FRAMES[k].format(k=_phrase(table, name, regime, k), v="\0", u=unit))])
    return reduce(lambda made, k: made.when(kind == k, sentence(k)), range(1, 4), F.when(kind == 0, sentence(0)))


def _split(text: str) -> list[str]:
    left, _, right = text.partition("\0")
    return [left, "\0", right]


def distractors(spark: SparkSession, sf_dir: str, most: int = 240) -> DataFrame:
    """One row with an array of English sentences from `documents`, those of least md5: bounded, so it may go to every task."""
    docs = _table(spark, sf_dir, "documents").where("lang = 'en' and text is not null")
    first = F.regexp_extract("text", r"^([A-Z][a-z ,]{40,220}\.)", 1)
    chosen = docs.select(first.alias("s")).where("s <> ''").distinct().orderBy(F.md5("s")).limit(most)
    return chosen.agg(F.array_sort(F.collect_list("s")).alias("pool"))


def _starts(a: Attribute) -> list[str] | None:
    """Texts of which one begins whatever the attribute's pattern finds; None if its pattern doesn't tell."""
    said = re.match(r"\(\?:([a-z |]+)\) ", a.pattern)
    plain = re.match(r"[a-z ]+(?=\()", a.pattern)
    return said[1].split("|") if said else [plain[0]] if plain else None


def _apart(table: str, name: str, regime: str, asked: list[Attribute]) -> bool:
    """Whether no statement of an attribute holds one of those asked, whatever its value, if the table's name and ends of sentences are not in it.

    What their patterns find begins with the table's name, so with the one in the statement's own phrase, and goes on as this does not.
    """
    starts = [_starts(a) for a in asked]
    if not all(s and all(x.startswith(table) for x in s) for s in starts):
        return False
    for k, frame in enumerate(_FRAMES):
        before, _, after = _split(frame.format(k=_phrase(table, name, regime, k), v="\0", u=_FACTS[table][name][1]))
        places = [i for i in range(len(before)) if before.startswith(table, i)]
        if not before.endswith(" ") or after[0] not in " ." or any(x in before or x in after or any(x.startswith(before[i:]) for i in places) for s in starts for x in s):
            return False
    return True


def _stated(rows: DataFrame, table: str, regime: str, asked: list[Attribute] | None = None) -> DataFrame:
    """(doc_key, domain, opening, facts): what documents say of their subjects, not yet among other sentences.

    With asked, attributes, comes (doc_key, domain, opening, n_facts, held, unheld, plain): held(at, s) are the statements that may hold one of these and their places
    among all, unheld are the tokens of the others, and plain is whether each statement held, and the opening, is one sentence.
    """
    kind = F.pmod(F.xxhash64("doc_key"), F.lit(4))
    said = {n: _said(table, n, regime, kind) for n in _FACTS[table]}
    root = _ROOT.get(table, "name")
    opening = F.concat(F.lit(f"This is the {table} profile of "), F.col(root).cast("string"), F.lit("."))
    if asked is None:
        return rows.select("doc_key", F.lit(table).alias("domain"), opening.alias("opening"), F.array_compact(F.array(*said.values())).alias("facts"))
    held, unheld, at, plain = [], F.lit(0).cast("bigint"), F.lit(0), F.lit(True) if root == "order_key" else _simple(opening)
    for n, s in said.items():
        entry, text = F.struct(at.alias("at"), s.alias("s")), _FACTS[table][n][0] == "string"
        there = _shown_value(table, n).isNotNull()
        if n in {a.name for a in asked} or not _apart(table, n, regime, asked):
            held.append(F.when(there, entry))
        else:
            odd = F.col(n).rlike(rf"{table}|[.!?\n]") if text else F.lit(False)
            held += [F.when(odd, entry)] if text else []
            unheld = unheld + F.when(there & ~odd, n_tokens(s)).otherwise(0)
        # A number's, a date's or a truth value's statement is one sentence, whatever its value.
        plain, at = plain & F.coalesce(_simple(s), F.lit(True)) if text else plain, at + there.cast("int")
    none = F.array().cast("array<struct<at:int,s:string>>")
    return rows.select("doc_key", F.lit(table).alias("domain"), opening.alias("opening"), at.alias("n_facts"), (F.array_compact(F.array(*held)) if held else none).alias("held"), unheld.alias("unheld"), plain.alias("plain"))


def _simple(statement: Column) -> Column:
    """Only a text with an end or a line feed inside one of its statements must be cut anew; else its sentences are the statements."""
    return ~statement.rlike(r"[.!?]\s|\n|^\P{L}|[^.!?]$")


def _rendered(stated: DataFrame, pool: DataFrame, corpus: str, padding: Column, shown: Callable[[Column], Column] | None = None) -> DataFrame:
    """Documents of stated facts. Short rows grow to long texts, and small files are read by few tasks, so they are dealt out before.

    With shown, a condition on a sentence, `parts`, a document's sentences in order, come in the text's place, but for sentences of the pool for which it
    doesn't hold: each of the pool is judged once, not once a document that draws it. stated then has held, not facts, as statements that cannot hold what is
    asked are told from their wording. `left_out` is how many tokens a document lacks by both.
    """
    place = lambda s, i: F.struct(F.xxhash64(F.col("doc_key"), s, i).alias("place"), s.alias("s"))
    ordered = lambda own: F.transform(F.sort_array(own), lambda x: x["s"])
    said = lambda body: F.concat_ws(" ", "opening", F.array_join(body, " "))
    columns = F.lit(corpus).alias("corpus"), "doc_key", "domain"
    if shown is None:
        rows = stated.repartition(int(stated.sparkSession.conf.get("spark.sql.shuffle.partitions")), "doc_key")
        draw = lambda j: F.pmod(F.xxhash64(F.col("doc_key"), j), F.greatest(F.size("pool"), F.lit(1)))
        noise = F.when((F.size("pool") > 0) & (padding > 0), F.transform(F.sequence(F.lit(1), padding), lambda j: F.element_at("pool", (draw(j) + 1).cast("int")))).otherwise(F.array().cast("array<string>"))
        return rows.crossJoin(F.broadcast(pool)).select(*columns, said(ordered(F.transform(F.concat("facts", noise), place))).alias("text"))
    judged = pool.select("pool", F.transform("pool", lambda s: F.coalesce(shown(s), F.lit(False))).alias("is_shown"), F.transform("pool", n_tokens).alias("sizes")).first()
    # The pool is bounded: it and the judgements are constants of the plan, and no document draws a shown sentence where there is none.
    pool, is_shown, sizes = (F.lit(x) for x in (judged.pool, judged.is_shown, judged.sizes)) if judged.pool else (None, None, None)
    draw = lambda j: (F.pmod(F.xxhash64(F.col("doc_key"), j), F.lit(len(judged.pool))) + 1).cast("int")
    numbers, none = F.sequence(F.lit(1), padding) if judged.pool else F.array().cast("array<int>"), F.lit(0).cast("bigint")
    lacks, own = F.aggregate(numbers, none, lambda n, j: n + F.element_at(sizes, draw(j))) if judged.pool else none, F.transform("held", lambda x: place(x["s"], x["at"]))
    if any(judged.is_shown):
        kept = F.filter(numbers, lambda j: F.element_at(is_shown, draw(j)))
        own = F.concat(own, F.transform(kept, lambda j: place(F.element_at(pool, draw(j)), F.col("n_facts") + j - 1)))
        lacks = lacks - F.aggregate(kept, none, lambda n, j: n + F.element_at(sizes, draw(j)))
    rows = stated.select(*columns, "opening", ordered(own).alias("body"), (lacks + F.col("unheld")).alias("left_out"), "plain", "n_facts")
    # The number of a document's statements is asked for too, so that what they are made of is read, held or not.
    parts = F.when(F.col("plain") & (F.col("n_facts") >= 0), F.concat(F.array("opening"), "body")).otherwise(sentences(said(F.col("body"))))
    return rows.select(*columns, parts.alias("parts"), "left_out")


PROFILE_TABLES = ("customer", "nation", "region", "supplier", "part")


def _of(rows: DataFrame, only: DataFrame | None) -> DataFrame:
    """Rows of the documents in only(doc_key), if given."""
    return rows if only is None else rows.join(only.select("doc_key"), "doc_key", "left_semi")


def profiles(spark: SparkSession, sf_dir: str, regime: str = "pattern", tables: tuple[str, ...] = PROFILE_TABLES, only: DataFrame | None = None) -> DataFrame:
    """Suite P: each profile has its facts, in wordings of the regime, among 0 to 12 other sentences."""
    pool = distractors(spark, sf_dir)
    padding = F.pmod(F.xxhash64("doc_key", F.lit("padding")), F.lit(13)).cast("int")
    return _rendered(reduce(DataFrame.unionByName, [_stated(_of(truth(spark, sf_dir, t), only), t, regime) for t in tables]), pool, "P", padding)


def dossiers(spark: SparkSession, sf_dir: str, regime: str = "pattern", only: DataFrame | None = None, pool: DataFrame | None = None, shown: Callable[[Column], Column] | None = None) -> DataFrame:
    """Suite C: long documents, a few facts in thousands of words of other text. pool: distractors, if they are known; shown: see _rendered."""
    rows = truth(spark, sf_dir, "order", only)
    if only is not None and shown is not None:
        # A few rows, each with hundreds of sentences to count: dealt out, or one task has them all.
        rows = rows.repartition(int(spark.conf.get("spark.sql.shuffle.partitions")), "doc_key")
    stated = _stated(rows, "order", regime, None if shown is None else list(shown.attributes))
    return _rendered(stated, distractors(spark, sf_dir) if pool is None else pool, "C", F.lit(260) + F.pmod(F.xxhash64("doc_key"), F.lit(120)).cast("int"), shown)


def dossier_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(corpus, doc_key) of the dossiers, from orders alone."""
    return _table(spark, sf_dir, "orders").select(F.lit("C").alias("corpus"), F.concat(F.lit("order:"), "o_orderkey").alias("doc_key"))


def pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Suite G: url and html as they are, one below the other."""
    return _table(spark, sf_dir, "pages").select(F.lit("G").alias("corpus"), F.concat(F.lit("page:"), "page_id").alias("doc_key"), F.lit("page").alias("domain"), F.concat_ws("\n", "url", "html").alias("text"))


def conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Dialogues as documents: turns in order."""
    turns = F.array_sort(F.collect_list(F.struct("turn", "role", "text")))
    return _table(spark, sf_dir, "conversations").groupBy("conv_id").agg(F.array_join(F.transform(turns, lambda t: F.concat_ws(": ", t["role"], t["text"])), "\n").alias("text")).select(
        F.lit("talk").alias("corpus"), F.concat(F.lit("talk:"), "conv_id").alias("doc_key"), F.lit("talk").alias("domain"), "text"
    )


def raw_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _table(spark, sf_dir, "documents").select(F.lit("raw").alias("corpus"), F.concat(F.lit("raw:"), "doc_id").alias("doc_key"), F.col("source").alias("domain"), "text")


def corpus(spark: SparkSession, sf_dir: str, name: str, regime: str = "pattern", only: DataFrame | None = None) -> DataFrame:
    """A suite by name; where(...) on it is the choice of documents before a query. With only(doc_key) no other document's text is made."""
    made = {"P": lambda: profiles(spark, sf_dir, regime, only=only), "G": lambda: _of(pages(spark, sf_dir), only), "C": lambda: dossiers(spark, sf_dir, regime, only), "talk": lambda: conversations(spark, sf_dir), "raw": lambda: raw_documents(spark, sf_dir)}
    return made[name]()


def specs(suite: str, regime: str = "pattern") -> dict[str, TableSpec]:
    if suite == "G":
        return {"page": PAGE}
    return {t: spec(t, regime) for t in (PROFILE_TABLES if suite == "P" else ("order",))}
