"""The systems compared with, each as settings of the engine or a reader of its own. Every one returns a Run: tuples, tokens by phase.

semantic_tree: a tree of headings, paragraphs and sentences; the node nearest an attribute's description, and in it the nearest sentence, is
read; filters by selectivity. declarative: fixed windows, the nearest few by description; filters by selectivity. full_scan: the whole document for each
filter that a lazy walk in the written order comes to, nothing kept between filters. plain_retrieval: one level, the description's own vector with a fixed
radius, written order. reader: no model; the first span of the right type in the sentence nearest the description. code_synthesis: patterns
induced from a few sampled sentences, then run everywhere. complete: this engine.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Sequence
from dataclasses import replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from docspj.engine import Engine, Run, Settings
from docspj.functions.text import distance_to, embed, md5_rank, n_tokens, norm2, sentences
from docspj.model import Attribute, Expr, Node, Query, TableSpec, attributes_of, predicate
from docspj.operators.index import TwoLevelIndex
from docspj.operators.retrieval import description, extract, finds, full_texts, gathered
from docspj.operators.segments import segment_fixed
from docspj.session import cut

NAMES = ("reader", "code_synthesis", "plain_retrieval", "declarative", "semantic_tree", "full_scan", "complete")
_SETTINGS = {
    "complete": Settings(),
    "plain_retrieval": Settings(retrieval="description", order="written", two_level=False, join="pushdown"),
    "declarative": Settings(retrieval="topk", topk=3, order="selectivity", join="pushdown"),
    "semantic_tree": Settings(retrieval="topk", topk=1, order="selectivity", join="pushdown"),
    "full_scan": Settings(retrieval="full", order="written", join="pushdown"),
}
_TYPED = {"double": r"(-?[0-9]+\.[0-9]+)", "bigint": r"(-?[0-9]+)", "date": r"([0-9]{4}-[0-9]{2}-[0-9]{2})", "boolean": r"\b(true|false)\b", "string": r"([A-Z][A-Za-z#_0-9]*[0-9#_][A-Za-z0-9#_]*|[A-Z]{2,}(?: [A-Z]+)*)"}


def baseline(name: str, index: TwoLevelIndex, specs: dict[str, TableSpec], **changes):
    """An object with run(query) -> Run. The index's texts are what all of them read; tree, windows and sentences are made from these."""
    if name == "reader":
        return _Direct(name, sentence_level(index), specs, **changes)
    if name == "code_synthesis":
        return _Direct(name, index, specs, **changes)
    settings = replace(_SETTINGS[name], **changes)
    if name == "full_scan":
        return _FullScan(index, specs, settings)
    if name == "semantic_tree":
        return _TreeEngine(semantic_tree(texts_of(index)), index, specs, settings)
    if name == "declarative":
        return Engine(windows(index), specs, settings)
    return Engine(index, specs, settings)


def texts_of(index: TwoLevelIndex) -> DataFrame:
    """(corpus, doc_key, text) of an index's documents, their segments one below the other."""
    return index.docs.select("corpus", "doc_key").join(full_texts(index.segments).select("doc_key", "text"), "doc_key").select("corpus", "doc_key", "text")


def _embedded(rows: DataFrame) -> DataFrame:
    return rows.withColumn("vec", embed(F.col("text"))).withColumn("n2", norm2(F.col("vec")))


def windows(index: TwoLevelIndex, tokens: int = 40) -> TwoLevelIndex:
    """The same documents in fixed windows."""
    return TwoLevelIndex(index.docs, cut(_embedded(segment_fixed(texts_of(index), tokens)), "windows"))


def sentence_level(index: TwoLevelIndex) -> TwoLevelIndex:
    """The same documents, a segment a sentence."""
    rows = texts_of(index).select("corpus", "doc_key", F.posexplode(sentences(F.col("text"))).alias("seg_no", "text"))
    return TwoLevelIndex(index.docs, cut(_embedded(rows.withColumn("n_tokens", n_tokens(F.col("text")))), "sentences"))


def semantic_tree(docs: DataFrame, sentences_a_node: int = 4) -> DataFrame:
    """(doc_key, node, heading, seg_no, text, n_tokens, vec, n2, node_vec, node_n2): the sentences of docs(doc_key, text) under their paragraphs and headings.

    A heading is an <h1> to <h6> line, a line that begins with #, or a line of at most eight words without a mark at its end. Paragraphs are parted by
    blank lines, headings and <p>; one of more than `sentences_a_node` sentences is parted further, as running text has no marks. A node's vector is its heading's and sentences' words.
    """
    line = F.transform(F.split("text", r"\n|(?i)(?=<p>|<h[1-6]>)"), F.trim)
    is_heading = lambda x: x.rlike(r"(?i)^<h[1-6]>|^#+\s") | ((x != "") & ~x.rlike(r"[.!?:;,>]$") & (F.size(F.split(x, r"\s+")) <= 8))
    start = F.struct(F.lit("").alias("heading"), F.lit(0).alias("part"), F.array().cast("array<struct<heading:string,part:int,sentence:string>>").alias("rows"))

    def step(s: Column, x: Column) -> Column:
        own = F.transform(sentences(x), lambda t: F.struct(s["heading"].alias("heading"), (s["part"] + x.rlike("(?i)^<p>").cast("int")).alias("part"), t.alias("sentence")))
        heading = F.struct(x.alias("heading"), (s["part"] + 1).alias("part"), F.concat(s["rows"], F.array(F.struct(x.alias("heading"), (s["part"] + 1).alias("part"), x.alias("sentence")))).alias("rows"))
        plain = F.struct(s["heading"].alias("heading"), (s["part"] + ((x == "") | x.rlike("(?i)^<p>")).cast("int")).alias("part"), F.concat(s["rows"], own).alias("rows"))
        return F.when(is_heading(x), heading).otherwise(plain)

    parted = docs.select("doc_key", F.posexplode(F.aggregate(line, start, step, lambda s: s["rows"])).alias("seg_no", "row"))
    within = Window.partitionBy("doc_key", "row.part").orderBy("seg_no")
    rows = parted.withColumn("node", F.concat_ws(".", "row.part", F.floor((F.row_number().over(within) - 1) / sentences_a_node).cast("string")))
    rows = _embedded(rows.select("doc_key", "node", F.col("row.heading").alias("heading"), "seg_no", F.col("row.sentence").alias("text"))).withColumn("n_tokens", n_tokens(F.col("text")))
    nodes = rows.groupBy(F.col("doc_key").alias("of"), F.col("node").alias("of_node")).agg(embed(F.concat_ws(" ", F.max("heading"), F.array_join(F.collect_list("text"), " "))).alias("node_vec"))
    return cut(rows.join(nodes, (F.col("doc_key") == F.col("of")) & (F.col("node") == F.col("of_node"))).drop("of", "of_node").withColumn("node_n2", norm2(F.col("node_vec"))), "tree")


def nearest_sentences(tree: DataFrame, docs: DataFrame, attributes: Sequence[Attribute], index: TwoLevelIndex) -> DataFrame:
    """One row a document, as `gathered`: for each attribute the sentence nearest its description in the node nearest it."""
    rows, best = tree, []
    for a in attributes:
        probe = index.vector(description(a))
        rows = rows.withColumns({f"node_{a.name}": distance_to(F.col("node_vec"), F.col("node_n2"), probe), f"sent_{a.name}": distance_to(F.col("vec"), F.col("n2"), probe)})
        best.append(F.min(F.struct(f"node_{a.name}", "node", f"sent_{a.name}", "seg_no"))["seg_no"].alias(f"best_{a.name}"))
    top = rows.groupBy(F.col("doc_key").alias("of")).agg(*best)
    flags = tree.join(top, F.col("doc_key") == F.col("of")).withColumns({f"near_{a.name}": F.col("seg_no") == F.col(f"best_{a.name}") for a in attributes})
    hits = flags.where(" or ".join(f"near_{a.name}" for a in attributes))
    return gathered(hits.select("doc_key", "seg_no", "text", "n_tokens", *[f"near_{a.name}" for a in attributes]), docs.select("doc_key"), [a.name for a in attributes])


class _TreeEngine(Engine):
    """An engine whose contexts come from the tree."""

    def __init__(self, tree: DataFrame, index: TwoLevelIndex, specs: dict[str, TableSpec], settings: Settings):
        super().__init__(index, specs, settings)
        self.tree = tree

    def located(self, attributes: Sequence[Attribute]) -> DataFrame:
        return nearest_sentences(self.tree, self.index.docs, attributes, self.index)


class _FullScan:
    """Each filter, and then each SELECT attribute or key, reads the whole document, even of an attribute read before: every mention is an attribute of its own."""

    def __init__(self, index: TwoLevelIndex, specs: dict[str, TableSpec], settings: Settings):
        self.index, self.specs, self.settings = index, specs, settings

    def run(self, q: Query) -> Run:
        specs, where = {}, {}
        for t in q.tables:
            copies: list[Attribute] = []

            def renamed(e: Expr, t: str = t, copies: list[Attribute] = copies) -> Expr:
                if isinstance(e, Node):
                    return Node(e.op, tuple(renamed(c) for c in e.children))
                copies.append(replace(self.specs[t][e.attr], name=f"{e.attr}__{len(copies)}"))
                return replace(e, attr=copies[-1].name)

            if t in q.where:
                where[t] = renamed(q.where[t])
            specs[t] = TableSpec(t, (*self.specs[t].attributes, *copies))
        return Engine(self.index, specs, self.settings).run(replace(q, where=where))


def induce(samples: Sequence[tuple[str, str]], width: int = 3) -> str | None:
    """A pattern of the commonest words before a value in (segment, value) samples; what follows is a value of the same kind."""
    before: Counter[str] = Counter()
    kinds: Counter[str] = Counter()
    for text, value in samples:
        at = text.find(value)
        if at > 0:
            before[" ".join(text[:at].split()[-width:])] += 1
            kinds[r"-?[0-9]+(?:\.[0-9]+)?" if re.fullmatch(r"-?[0-9.]+", value) else r"[A-Za-z0-9#_-]+"] += 1
    if not before:
        return None
    return re.escape(before.most_common(1)[0][0]) + r"\s+(" + kinds.most_common(1)[0][0] + ")"


class _Direct:
    """Readers without a lazy plan: every attribute from every document, then plain filters and joins."""

    def __init__(self, name: str, index: TwoLevelIndex, specs: dict[str, TableSpec], sample: int = 20, seed: str = "code"):
        self.name, self.index, self.specs, self.sample, self.seed = name, index, specs, sample, seed

    def run(self, q: Query) -> Run:
        run, parts = Run(None, docs=self.index.docs.count()), {}  # type: ignore[arg-type]
        for t in q.tables:
            names = list(dict.fromkeys([*q.selected(t), *attributes_of(q.tree(t)), *q.keys(t)]))
            attributes = [self.specs[t][n] for n in names]
            rows = self.read(attributes) if self.name == "reader" else self.synthesised(attributes, run)
            some = " or ".join(f"v_{n} is not null" for n in names)
            parts[t] = rows.where(some).where(predicate(q.where.get(t), {n: F.col(f"v_{n}") for n in names}))
        done = None
        for t in q.tables:
            own = parts[t].select(*[F.col(f"v_{n}").alias(f"{t}.{n}") for n in dict.fromkeys([*q.selected(t), *q.keys(t)])])
            links = [e for e in q.edges if t in (e.left, e.right) and done is not None and f"{e.other(t)[1]}.{e.other(t)[2]}" in done.columns]
            done = own if done is None else done.join(own, [F.col(f"`{e.left}.{e.left_attr}`") == F.col(f"`{e.right}.{e.right_attr}`") for e in links])
        run.tuples = done.select(*[F.col(f"`{t}.{a}`").alias(f"{t}.{a}" if len(q.tables) > 1 else a) for t, a in q.select])
        return run

    def read(self, attributes: Sequence[Attribute]) -> DataFrame:
        """The first span of the attribute's type in the sentence nearest its description."""
        typed = [Attribute(a.name, a.description, a.dtype, _TYPED[a.dtype]) for a in attributes]
        near = None
        for a in typed:
            best = best_sentence(self.index, a).select(F.col("doc_key").alias("of"), extract(F.col("text"), a).alias(f"v_{a.name}"))
            near = best.withColumnRenamed("of", "doc_key") if near is None else near.join(best, F.col("doc_key") == F.col("of")).drop("of")
        return near

    def synthesised(self, attributes: Sequence[Attribute], run: Run) -> DataFrame:
        """Patterns from the segments of a few sampled documents; only these are paid for."""
        rows = self.index.segments
        for a in attributes:
            rows = rows.withColumn(f"is_{a.name}", finds(F.col("text"), a))
        held = rows.where(" or ".join(f"is_{a.name}" for a in attributes)).orderBy(md5_rank(F.col("doc_key"), self.seed), "doc_key", "seg_no").limit(self.sample * len(attributes))
        seen = held.select("text", "n_tokens", *[extract(F.col("text"), Attribute(a.name, "", "string", a.pattern)).alias(f"v_{a.name}") for a in attributes]).collect()
        run.charge("sample", sum(r.n_tokens for r in seen))
        made = {a.name: induce([(r.text, r[f"v_{a.name}"]) for r in seen if r[f"v_{a.name}"]]) for a in attributes}
        flags = self.index.segments.withColumns({f"near_{a.name}": F.col("text").rlike(made[a.name]) if made[a.name] else F.lit(False) for a in attributes})
        docs = gathered(flags.select("doc_key", "seg_no", "text", F.lit(0).alias("n_tokens"), *[f"near_{a.name}" for a in attributes]), self.index.docs.select("doc_key"), [a.name for a in attributes])
        typed = [Attribute(a.name, "", a.dtype, made[a.name] or "(?!)()") for a in attributes]
        return cut(docs.select("doc_key", *[extract(F.col(f"text_{a.name}"), a).alias(f"v_{a.name}") for a in typed]), "synthesised")


def best_sentence(index: TwoLevelIndex, a: Attribute) -> DataFrame:
    """(doc_key, text) of the segment nearest an attribute's description."""
    probe = index.vector(description(a))
    near = index.segments.select("doc_key", F.struct(distance_to(F.col("vec"), F.col("n2"), probe).alias("d"), "seg_no", "text").alias("s"))
    return near.groupBy("doc_key").agg(F.min("s").alias("s")).select("doc_key", "s.text")
