"""Queries over virtual tables: retrieve, sample, order, read lazily, join by membership filters.

What has been read of a document is in its map `values`; an attribute is paid for when it enters the map, and never again. Filters,
keys and SELECT attributes are all read this way, so what a query costs is what was asked of the reader.
"""

from __future__ import annotations

import hashlib
import itertools
from collections.abc import Callable, Sequence
from dataclasses import dataclass, field
from datetime import date

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from docspj.functions.text import n_tokens
from docspj.model import Attribute, Edge, Expr, Leaf, Query, TableSpec, all_of, attributes_of, leaves, normalise, predicate, test
from docspj.operators.extractors import ExtractionCache, read_batch
from docspj.operators.index import TwoLevelIndex
from docspj.operators.lazy import TokenModel, fold_executor, in_selectivity, join_selectivity, planned, round_executor, row_executor
from docspj.operators.retrieval import Probes, extract, fit_probes, retrieve, retrieve_full, retrieve_located, retrieve_topk, sample_docs, sampled_texts
from docspj.plans.costs import combine
from docspj.plans.ordering import plan_node
from docspj.session import cut
from docspj.sqlfront import parse

RETRIEVALS = ("evidence", "description", "synthetic", "located", "full", "topk")
EXECUTORS = ("fold", "row", "rounds")
_PYTHON = {"bigint": int, "double": float, "date": date.fromisoformat, "boolean": lambda t: t == "true"}
_NOTHING = "map<string,string>"


@dataclass
class Settings:
    """retrieval: how an attribute's text is found. order: ARMS of plans.ordering. rate, k, margin: sample share, centres, slack of radii.

    executor: fold evaluates a rule in the plan; row and rounds call a reader. search: how segments near the evidence are found. gamma: a radius
    for all attributes instead of fitted ones. most_members: membership filters beyond it go to the rounds, where they are joins. measure_gap: sum what filters
    are expected to cost beside what they do.
    """

    retrieval: str = "evidence"
    order: str = "adaptive"
    join: str = "adaptive"
    two_level: bool = True
    rate: float = 0.05
    least_sample: int = 10
    k: int = 3
    topk: int = 3
    margin: float = 0.1
    tau: float | None = None
    tau_shift: float = 0.0
    gamma: float | None = None
    seed: str = "sample"
    gamma_mode: str = "diameter"
    search: str = "scan"
    executor: str = "fold"
    most_members: int = 1_000_000
    measure_gap: bool = False


@dataclass
class Run:
    """Tuples, and what they cost: tokens by phase (output is the answers' own), calls, documents of the whole set. steps: tables as they were joined;
    shares: chances of the membership filters; expected: tokens that the filters' orders foresaw, if asked for."""

    tuples: DataFrame
    tokens: dict[str, int] = field(default_factory=dict)
    calls: int = 0
    docs: int = 0
    steps: list[str] = field(default_factory=list)
    probes: dict[str, Probes] = field(default_factory=dict)
    expected: float = 0.0
    shares: list[float] = field(default_factory=list)

    @property
    def total(self) -> int:
        return sum(self.tokens.values())

    def charge(self, phase: str, tokens: int | None, out: int | None = 0, calls: int | None = 0) -> None:
        self.tokens[phase] = self.tokens.get(phase, 0) + int(tokens or 0)
        self.tokens["output"] = self.tokens.get("output", 0) + int(out or 0)
        self.calls += int(calls or 0)


@dataclass
class Side:
    """A table in a query: docs(doc_key, cost_<a>, text_<a>, values), its tree; sample(doc_key, v_<a>); selectivities and mean costs from it."""

    spec: TableSpec
    docs: DataFrame
    tree: Expr | None
    names: list[str]
    sample: DataFrame | None = None
    p: dict[int, float] = field(default_factory=dict)
    mean: dict[str, float] = field(default_factory=dict)

    @property
    def chance(self) -> float:
        def of(e: Expr) -> float:
            return self.p.get(e.id, 0.5) if isinstance(e, Leaf) else combine(e.op, [of(c) for c in e.children])

        return 1.0 if self.tree is None else of(self.tree)


def _known(a: str) -> Column:
    return F.map_contains_key("values", F.lit(a))


def _price(a: str) -> Column:
    """Tokens that reading an attribute costs now: nothing if it is known."""
    return F.when(_known(a), 0).otherwise(F.coalesce(f"cost_{a}", F.lit(0))).cast("bigint")


class Engine:
    """specs: virtual tables over the index's documents. extractor(text column, attribute) -> value column is the rule that the fold executor evaluates.

    reader(attribute name, text) -> value as text or None stands for a model, one for all tables or one each: the row executor calls it for a document when a
    test needs it, the rounds in batches. Of a document of the sample it is asked for several attributes at once, names joined by commas and values by line feeds.
    cache holds what was read for later queries; what it holds costs nothing.
    """

    def __init__(
        self, index: TwoLevelIndex, specs: dict[str, TableSpec], settings: Settings | None = None, extractor: Callable[[Column, Attribute], Column] = extract,
        reader: dict[str, Callable[[str, str], str | None]] | Callable[[str, str], str | None] | None = None, cache: ExtractionCache | None = None, model: TokenModel | None = None,
    ):
        self.index, self.specs, self.settings, self.extractor = index, specs, settings or Settings(), extractor
        self.reader, self.cache, self.model = reader, cache, model or TokenModel()
        self.found: dict[tuple, tuple[DataFrame, DataFrame | None, Probes | None]] = {}
        self.n_docs: int | None = None

    @property
    def samples(self) -> bool:
        """Whether anything that the settings ask for rests on a sample."""
        s = self.settings
        plain = s.order in ("written", "random") and (s.join in ("pushdown", "random") or s.join.startswith("fixed"))
        return s.retrieval in ("evidence", "synthetic") or not plain

    def contexts(self, table: str, names: Sequence[str]) -> tuple[DataFrame, DataFrame | None, Probes | None]:
        """One row a document: the text found for each attribute, and its tokens; nothing is read. And the sample's keys, and probes. Kept for later queries of the same attributes."""
        s = self.settings
        key = (table, tuple(sorted(names)), s.retrieval, s.two_level, s.rate, s.k, s.topk, s.margin, s.tau, s.tau_shift, s.gamma, s.gamma_mode, s.seed, s.least_sample, s.search, self.samples)
        if key in self.found:
            return self.found[key]
        spec, probes, sample = self.specs[table], None, None
        attributes = [spec[n] for n in sorted(names)]
        if s.retrieval in ("evidence", "description", "synthetic"):
            probes = fit_probes(self.index, attributes, rate=s.rate, k=s.k, probes=s.retrieval, margin=s.margin, seed=s.seed, gamma_mode=s.gamma_mode, least=s.least_sample)
            if s.tau is not None:
                probes.thresholds.tau = s.tau
            probes.thresholds.tau += s.tau_shift
            if s.gamma is not None:
                probes.thresholds.gamma = dict.fromkeys(probes.thresholds.gamma, s.gamma)
            sample, rows = probes.sample, retrieve(self.index, attributes, probes, s.two_level, s.search)
        else:
            rows = self.located(attributes)
        if sample is None and self.samples:
            sample = cut(sample_docs(self.index.docs, s.rate, s.seed, s.least_sample).select("doc_key"), "sampled")
        if sample is not None:
            # A call that reads a whole document answers for all of its attributes.
            texts = sampled_texts(self.index, sample, attributes if s.executor == "fold" and self.extractor is extract else ())
            if s.executor == "fold":
                sample = texts.select("doc_key", "n_tokens", *[self.extractor(F.col("text"), a).alias(f"v_{a.name}") for a in attributes])
            else:
                asked = texts.select("doc_key", F.lit(",".join(a.name for a in attributes)).alias("attr"), "text")
                answers = cut(self.batch(table)(asked), "sampled").join(texts.select("doc_key", "n_tokens"), "doc_key")
                parts = F.split("value", "\n")
                sample = answers.select("doc_key", "n_tokens", *[self.typed(F.nullif(F.try_element_at(parts, F.lit(i + 1)), F.lit("")), a).alias(f"v_{a.name}") for i, a in enumerate(attributes)])
            sample = cut(sample, "sample")
        self.found[key] = cut(rows.select("doc_key", *[f"cost_{a.name}" for a in attributes], *[f"text_{a.name}" for a in attributes]), "contexts"), sample, probes
        return self.found[key]

    def located(self, attributes: Sequence[Attribute]) -> DataFrame:
        """Contexts of the arms that fit nothing."""
        if self.settings.retrieval == "topk":
            return retrieve_topk(self.index, attributes, self.settings.topk)
        return (retrieve_full if self.settings.retrieval == "full" else retrieve_located)(self.index, attributes)

    @staticmethod
    def typed(text: Column, a: Attribute) -> Column:
        return text if a.dtype == "string" else text.try_cast(a.dtype)

    def side(self, query: Query, table: str, run: Run) -> Side:
        """Contexts, and in one pass over the sample the selectivities of the tree's leaves and mean costs."""
        tree = query.tree(table)
        names = list(dict.fromkeys([*query.selected(table), *attributes_of(tree), *query.keys(table)]))
        docs, sample, probes = self.contexts(table, names)
        if probes is not None:
            run.probes[table] = probes
        held = F.create_map().cast(_NOTHING)
        if self.cache is not None:
            before = self.cache.rows().where(F.col("attr").isin([f"{table}.{n}" for n in names])).select("doc_key", F.struct(F.substring("attr", len(table) + 2, 10_000).alias("key"), "value").alias("entry"))
            docs = docs.join(before.groupBy(F.col("doc_key").alias("of")).agg(F.map_from_entries(F.collect_set("entry")).alias("held")), F.col("doc_key") == F.col("of"), "left").drop("of")
            held = F.coalesce("held", held)
        side = Side(self.specs[table], docs.withColumn("values", held).drop("held"), tree, names)
        if sample is None:
            return side
        side.sample = sample.where(" or ".join(f"v_{n} is not null" for n in names))
        out = sum((self.out(F.col(f"v_{n}").cast("string")) for n in names), F.lit(0))
        leaf = [F.avg(test(x, F.col(f"v_{x.attr}")).cast("double")).alias(f"p{x.id}") for x in leaves(tree)]
        costs = [F.avg(F.coalesce(f"cost_{n}", F.lit(0))).alias(f"c_{n}") for n in names]
        row = side.sample.join(docs, "doc_key", "left").agg(F.count(F.lit(1)).alias("n"), *leaf, *costs).first()
        paid = sample.agg(F.sum("n_tokens").alias("t"), F.sum(out).alias("out"), F.count(F.lit(1)).alias("n")).first()
        run.charge("sample", (paid.t or 0) + self.model.prompt * paid.n, paid.out, paid.n)
        side.p = {x.id: row[f"p{x.id}"] if row.n else 0.5 for x in leaves(tree)}
        side.mean = {n: row[f"c_{n}"] or 0.0 for n in names}
        return side

    def sql(self, text: str) -> DataFrame:
        """The tuples of a query given as text."""
        return self.run(parse(text)).tuples

    def run(self, query: Query) -> Run:
        if self.settings.executor not in EXECUTORS or (self.settings.executor != "fold" and self.reader is None):
            raise ValueError(f"executor {self.settings.executor} is unknown, or lacks a reader")
        if self.n_docs is None:
            self.n_docs = self.index.docs.count()
        run = Run(None, docs=self.n_docs)  # type: ignore[arg-type]
        sides = {t: self.side(query, t, run) for t in query.tables}
        if len(query.tables) == 1:
            t = query.tables[0]
            rows = self.read(sides[t], self.filtered(sides[t], run, query.selected(t)), query.selected(t), run, "select")
            run.tuples = rows.select("doc_key", *[self.value(sides[t], a).alias(a) for a in query.selected(t)])
            return run
        return self.joined(query, sides, run)

    def out(self, value: Column) -> Column:
        """Tokens of an answer."""
        return n_tokens(value) if self.model.count_output else F.lit(0)

    def value(self, side: Side, a: str) -> Column:
        """A known attribute's value."""
        return self.typed(F.try_element_at("values", F.lit(a)), side.spec[a])

    def rule(self, side: Side, a: str) -> Column:
        """An attribute's value: what is known, or what the rule reads in its text; null where there is no text."""
        return F.when(_known(a), self.value(side, a)).when(F.coalesce(f"cost_{a}", F.lit(0)) > 0, self.extractor(F.col(f"text_{a}"), side.spec[a]))

    def paid(self, done: DataFrame, run: Run, phase: str) -> None:
        """Charge a phase's rows(tokens, calls, out)."""
        row = done.agg(F.sum("tokens").alias("t"), F.sum("calls").alias("c"), F.sum("out").alias("o")).first()
        run.charge(phase, (row.t or 0) + self.model.prompt * (row.c or 0), row.o, row.c)

    def entered(self, side: Side, fresh: list[tuple[Column, str]]) -> Column:
        """The map entries of attributes that the rule reads now: (whether, attribute) pairs."""
        entries = [F.when(on & ~_known(a), F.struct(F.lit(a).alias("key"), self.rule(side, a).cast("string").alias("value"))) for on, a in fresh]
        return F.array_compact(F.array(*entries))

    def remember(self, side: Side, before: DataFrame, after: DataFrame) -> None:
        """Into the cache: what rows of after know that before, the state they were read from, did not. after has `new` entries."""
        if self.cache is not None:
            rows = after.select("doc_key", F.explode("new").alias("e"), *[c for c in after.columns if c.startswith("cost_")])
            price = F.coalesce(*[F.when(F.col("e.key") == n, F.col(f"cost_{n}")) for n in side.names], F.lit(0)).cast("bigint")
            self.cache.put(rows.select("doc_key", F.concat(F.lit(f"{side.spec.name}."), F.col("e.key")).alias("attr"), F.col("e.value").alias("value"), price.alias("tokens_in"), self.out(F.col("e.value")).cast("bigint").alias("tokens_out")))

    def reads(self, table: str) -> Callable[[str, str], str | None]:
        return self.reader[table] if isinstance(self.reader, dict) else self.reader  # type: ignore[return-value]

    def batch(self, table: str) -> Callable[[DataFrame], DataFrame]:
        return lambda rows: read_batch(rows, self.reads(table))

    def read(self, side: Side, rows: DataFrame, names: Sequence[str], run: Run, phase: str) -> DataFrame:
        """rows with these attributes known. Those not known before are read, and charged, now."""
        names = list(dict.fromkeys(names))
        if not names:
            return rows
        tokens, calls = (sum((x(_price(a)) for a in names), F.lit(0)).cast("bigint") for x in (lambda c: c, lambda c: (c > 0).cast("bigint")))
        priced = rows.withColumns({"tokens": tokens, "calls": calls})
        if self.settings.executor == "fold":
            new = self.entered(side, [(F.lit(True), a) for a in names])
        else:
            wanted = F.array_compact(F.array(*[F.when(_price(a) > 0, F.struct(F.lit(a).alias("attr"), F.col(f"text_{a}").alias("text"))) for a in names]))
            answers = cut(self.batch(side.spec.name)(rows.select("doc_key", F.inline(wanted))), f"{phase}-answers")
            held = answers.groupBy(F.col("doc_key").alias("of")).agg(F.collect_list(F.struct(F.col("attr").alias("key"), "value")).alias("read"))
            priced = priced.join(held, F.col("doc_key") == F.col("of"), "left").drop("of")
            entries = F.map_from_entries(F.coalesce("read", F.array().cast("array<struct<key:string,value:string>>")))
            new = F.array_compact(F.array(*[F.when(~_known(a), F.struct(F.lit(a).alias("key"), F.try_element_at(entries, F.lit(a)).alias("value"))) for a in names]))
        return self.settled(side, priced.withColumn("new", new).drop("read"), run, phase)

    def settled(self, side: Side, done: DataFrame, run: Run, phase: str) -> DataFrame:
        """rows(tokens, calls, new, values) durably written, charged, remembered; new entries are known from here on. `kept` stays, if there."""
        out = F.aggregate("new", F.lit(0).cast("bigint"), lambda s, e: s + self.out(e["value"]))
        done = cut(done.withColumns({"out": out, "values": F.map_concat("values", F.map_from_entries("new"))}), phase)
        self.paid(done, run, phase)
        self.remember(side, done, done)
        return done.drop("tokens", "calls", "out", "new")

    def filtered(self, side: Side, run: Run, select: Sequence[str] = (), members: DataFrame | None = None, key: str = "", phase: str = "filter") -> DataFrame:
        """Documents of a side that pass its filters; and, with members(member), distinct values of `key`, a membership filter that competes with them."""
        s, tree, p = self.settings, side.tree, dict(side.p)
        if members is not None:
            own = Leaf(key, "in", ())
            tree = normalise(own if tree is None else all_of(own, tree))
            run.shares.append(self.share(side, key, members))
            p = {1: run.shares[-1]} | {i + 1: q for i, q in p.items()}
        if tree is None:
            return side.docs
        p = {x.id: p.get(x.id, 0.5) for x in leaves(tree)}
        names = attributes_of(tree)
        cost = {a: _price(a) for a in names}
        options = {"selected": select} if members is None and s.order == "adaptive" else {}
        if s.order == "average_cost":
            options["averages"] = side.mean
        rows = planned(side.docs, tree, cost, p, s.order, seed=s.seed, **options)
        if s.measure_gap and side.sample is not None and s.order == "adaptive":
            run.expected += rows.agg(F.sum(plan_node(tree, cost, p)["c"])).first()[0] or 0.0
        executor = s.executor
        if executor == "row" and members is not None and members.limit(s.most_members + 1).count() > s.most_members:
            executor = "rounds"
        if executor == "fold":
            truths = {}
            if members is not None:
                # The rule costs nothing: membership is a join over all documents, and the walk decides who is charged for it.
                rows = rows.join(members, self.rule(side, key) == F.col("member"), "left").withColumn("is_in", F.col("member").isNotNull()).drop("member")
                truths = {1: F.col("is_in")}
            done = fold_executor(rows, tree, {a: self.rule(side, a) for a in names}, cost, (), truths)
            done = done.withColumn("new", self.entered(side, [(F.array_contains("read_attrs", a), a) for a in names])).drop("select_tokens", "read_attrs", "is_in")
        else:
            priced = rows.withColumns({f"price_{a}": c for a, c in cost.items()} | {"before": F.map_keys("values")})
            context, prices = {a: f"text_{a}" for a in names}, {a: f"price_{a}" for a in names}
            if executor == "row":
                held = None if members is None else frozenset(r[0] for r in members.limit(s.most_members).collect())
                parsers = {a: _PYTHON[side.spec[a].dtype] for a in names if side.spec[a].dtype in _PYTHON}
                done = row_executor(priced, tree, context, prices, self.reads(side.spec.name), priced.columns, parsers, held)
            else:
                typed = {a: (lambda t, a=a: self.typed(t, side.spec[a])) for a in names}
                done = round_executor(priced, "doc_key", tree, context, prices, self.batch(side.spec.name), typed, lambda d: cut(d, phase), members)
            # The walk's map holds what was known and what it read.
            new = F.filter(F.map_entries("values"), lambda e: ~F.array_contains("before", e["key"]))
            done = done.withColumn("new", new).withColumn("values", F.map_filter("values", lambda k, v: F.array_contains("before", k))).drop("before", *prices.values())
        return self.settled(side, done.drop("plan"), run, phase).where("kept").drop("kept")

    def share(self, side: Side, key: str, members: DataFrame) -> float:
        """Share of a side's sample whose key is among the members."""
        if side.sample is None:
            return 0.5
        return in_selectivity(side.sample.where(F.col(f"v_{key}").isNotNull()), f"v_{key}", members.select(F.col("member").alias("value")))

    def expected(self, side: Side, key: str = "", p_in: float | None = None) -> tuple[float, float]:
        """Sums over a side's documents: of the expected cost of its filters, with a membership filter of chance p_in among them if given; and of the key's cost."""
        tree, p = side.tree, dict(side.p)
        if p_in is not None:
            own = Leaf(key, "in", ())
            tree, p = normalise(own if tree is None else all_of(own, tree)), {1: p_in} | {i + 1: q for i, q in p.items()}
        cost = {a: _price(a) for a in side.names}
        filters = plan_node(tree, cost, {x.id: p.get(x.id, 0.5) for x in leaves(tree)})["c"] if tree is not None else F.lit(0.0)
        row = side.docs.agg(F.sum(filters), F.sum(cost[key]) if key else F.lit(0)).first()
        return float(row[0] or 0), float(row[1] or 0)

    def joined(self, query: Query, sides: dict[str, Side], run: Run) -> Run:
        mode = self.settings.join
        done: dict[str, DataFrame] = {}
        if mode == "pushdown":
            for t in query.tables:
                done[t] = self.read(sides[t], self.filtered(sides[t], run), query.keys(t), run, "join")
            for e in query.edges:
                self.reduce(e, sides, done)
        else:
            plan = mode.split(":")[1].split(",") if ":" in mode else None
            edges = list(query.edges)
            if plan is not None:
                first, second = plan[:2]
                edge = next(e for e in edges if {e.left, e.right} == {first, second})
            elif mode == "random":
                edge = min(edges, key=lambda e: hashlib.md5(f"{self.settings.seed}:{e}".encode()).hexdigest())
                first, second = self.direction(edge, sides)[1]
            else:
                priced = [(*self.direction(e, sides), i) for i, e in enumerate(edges)]
                _, (first, second), i = min(priced, key=lambda x: (x[0], x[2]))
                edge = edges[i]
            run.steps.append(first)
            done[first] = self.read(sides[first], self.filtered(sides[first], run), [edge.other(first)[0]], run, "join")
            self.bring(second, query, sides, done, run, edge)
            while len(done) < len(query.tables):
                near = dict(query.graph.between(set(done)))
                if plan is not None:
                    nxt = plan[len(done)]
                elif mode == "random":
                    nxt = min(near, key=lambda t: hashlib.md5(f"{self.settings.seed}:{t}".encode()).hexdigest())
                else:
                    nxt = min(near, key=lambda t: self.next_price(t, near[t], sides, done))
                self.bring(nxt, query, sides, done, run)
        # Which documents make tuples is known from keys alone; only these are read for what is selected.
        tuples, held = None, set()
        for t in query.tables:
            part = done[t].select(F.col("doc_key").alias(f"{t}.doc_key"), *[self.value(sides[t], k).alias(f"{t}.{k}") for k in query.keys(t)])
            links = [e for e in query.edges if {e.left, e.right} <= held | {t} and t in (e.left, e.right)]
            if tuples is not None and not links:
                raise ValueError("tables must be named in an order in which each joins one named before")
            tuples = part if tuples is None else tuples.join(part, [F.col(f"`{e.left}.{e.left_attr}`") == F.col(f"`{e.right}.{e.right_attr}`") for e in links])
            held.add(t)
        tuples = cut(tuples.select(*[f"`{t}.doc_key`" for t in query.tables]), "tuples")
        for t in query.tables:
            names = query.selected(t)
            if not names:
                continue
            own = done[t].join(tuples.select(F.col(f"`{t}.doc_key`").alias("of")).distinct(), F.col("doc_key") == F.col("of"), "left_semi")
            rows = self.read(sides[t], own, names, run, "select")
            tuples = tuples.join(rows.select(F.col("doc_key").alias(f"{t}.of"), *[self.value(sides[t], a).alias(f"{t}.{a}") for a in names]), F.col(f"`{t}.doc_key`") == F.col(f"`{t}.of`"))
        run.tuples = tuples.select(*[F.col(f"`{t}.{a}`") for t, a in query.select])
        return run

    def members(self, side: Side, rows: DataFrame, key: str) -> DataFrame:
        return rows.select(self.value(side, key).alias("member")).where("member is not null").distinct()

    def bring(self, table: str, query: Query, sides: dict[str, Side], done: dict[str, DataFrame], run: Run, edge: Edge | None = None) -> None:
        """Join a table next to the joined ones: their keys become its membership filter, and its survivors reduce them."""
        links = [e for e in query.edges if table in (e.left, e.right) and e.other(table)[1] in done]
        links = links if edge is None else [edge, *[e for e in links if e != edge]]
        run.steps.append(table)
        for at, e in enumerate(links):
            own, other, theirs = e.other(table)
            done[other] = self.read(sides[other], done[other], [theirs], run, "join")
            if at == 0:
                done[table] = self.filtered(sides[table], run, (), self.members(sides[other], done[other], theirs), own, "join")
            # Further edges between joined tables leave what has a partner over them.
            done[table] = self.read(sides[table], done[table], [own], run, "join")
            self.reduce(e, sides, done)

    def reduce(self, e: Edge, sides: dict[str, Side], done: dict[str, DataFrame]) -> None:
        """Both ends of an edge whose keys are known keep documents that have a partner."""
        ends = ((e.left, e.left_attr, e.right, e.right_attr), (e.right, e.right_attr, e.left, e.left_attr))
        new = {t: done[t].join(self.members(sides[o], done[o], b), self.value(sides[t], a) == F.col("member"), "left_semi") for t, a, o, b in ends}
        done |= new

    def direction(self, e: Edge, sides: dict[str, Side]) -> tuple[float, tuple[str, str]]:
        """An edge's cost before anything is read, and (first, second) table: the side of lesser filters and keys goes first; its price is these and
        the other side's documents with the membership filter, at the chance that the samples show."""
        terms = {}
        for t, key in ((e.left, e.left_attr), (e.right, e.right_attr)):
            filters, keys = self.expected(sides[t], key)
            terms[t] = filters + sides[t].chance * keys
        first, second = (e.left, e.right) if terms[e.left] < terms[e.right] else (e.right, e.left)
        own, _, theirs = e.other(second)
        return terms[first] + self.expected(sides[second], own, self.met(sides[first], theirs, sides[second], own))[0], (first, second)

    def met(self, first: Side, theirs: str, second: Side, own: str) -> float:
        """Share of the second side's sample that meets a key of the first one's sample: an estimate before anything is run."""
        if first.sample is None or second.sample is None:
            return 0.5
        passed = first.sample if first.tree is None else first.sample.where(predicate_of(first))
        return join_selectivity(passed.where(F.col(f"v_{theirs}").isNotNull()), f"v_{theirs}", second.sample.where(F.col(f"v_{own}").isNotNull()), f"v_{own}")

    def next_price(self, table: str, links: list[Edge], sides: dict[str, Side], done: dict[str, DataFrame]) -> float:
        """Expected tokens of a table with its membership filter, and of the joined side's key that is still to be read.

        Where that key is known its values give the filter's chance on the sample; else the joined side's sample does.
        """
        own, other, theirs = links[0].other(table)
        rest = done[other].agg(F.coalesce(F.sum(_price(theirs)), F.lit(0)).alias("t"), F.count_if(~_known(theirs)).alias("n")).first()
        p_in = self.share(sides[table], own, self.members(sides[other], done[other], theirs)) if rest.n == 0 else self.met(sides[other], theirs, sides[table], own)
        return self.expected(sides[table], own, p_in)[0] + float(rest.t)


def predicate_of(side: Side) -> Column:
    """A side's tree over its sample's values."""
    return predicate(side.tree, {a: F.col(f"v_{a}") for a in side.names})


def left_deep_orders(query: Query) -> list[list[str]]:
    """Every order in which each table joins one before it."""
    found = []
    for order in itertools.permutations(query.tables):
        if all(any({e.left, e.right} <= {t, *order[:i]} and t in (e.left, e.right) for e in query.edges) for i, t in enumerate(order) if i):
            found.append(list(order))
    return found


def best_order(engine: Engine, query: Query) -> Run:
    """The known-selectivity optimum: the cheapest, as realised, of pushdown and all left-deep orders."""
    runs, kept = [], engine.settings.join
    for mode in ["pushdown", *[f"fixed:{','.join(o)}" for o in left_deep_orders(query)]]:
        engine.settings.join = mode
        runs.append(engine.run(query))
    engine.settings.join = kept
    return min(runs, key=lambda r: r.total)
