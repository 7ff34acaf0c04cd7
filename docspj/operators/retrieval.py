"""Evidence-augmented retrieval: sample, evidence, thresholds, segments near the evidence of an attribute."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterable, Sequence
from dataclasses import dataclass, field
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from docspj.functions.text import distance_to, md5_rank, n_tokens, python_embed, unit
from docspj.model import Attribute
from docspj.operators import batches
from docspj.operators.index import TwoLevelIndex, kmeans_centres
from docspj.session import cut

TAU0 = 1.45
MARGIN = 0.1
PROBES = ("evidence", "description", "synthetic")


def extract(text: Column, a: Attribute) -> Column:
    """The rule extractor: the pattern's first group, or a count or presence of it, cast to the attribute's type; null if not found."""
    if a.pattern.startswith("count:"):
        raw = F.regexp_count(text, F.lit(a.pattern[6:])).cast("string")
    elif a.pattern.startswith("has:"):
        raw = text.rlike(a.pattern[4:]).cast("string")
    else:
        raw = F.nullif(F.regexp_extract(text, a.pattern, 1), F.lit(""))
    return raw if a.dtype == "string" else raw.try_cast(a.dtype)


def finds(text: Column, a: Attribute) -> Column:
    """Whether a segment holds the attribute."""
    return text.rlike(a.pattern.split(":", 1)[1] if a.pattern.startswith(("count:", "has:")) else a.pattern)


@dataclass
class Thresholds:
    tau: float = TAU0
    gamma: dict[str, float] = field(default_factory=dict)


@dataclass
class Probes:
    """What a query searches with: its own embedding, the centres of each attribute, the fitted radii, and what fitting them cost. ranked: (doc_key, doc_dist) of all documents, if known."""

    query: list[float]
    centres: dict[str, list[list[float]]]
    thresholds: Thresholds
    evidence: dict[str, int] = field(default_factory=dict)
    sample_docs: int = 0
    sample_tokens: int = 0
    sample: DataFrame | None = None
    ranked: DataFrame | None = None


def description(a: Attribute) -> str:
    return f"{a.name.replace('_', ' ')} {a.description}"


def hashed(text: str) -> list[float]:
    return unit(python_embed(text))


def query_embedding(attributes: Sequence[Attribute], vector: Callable[[str], list[float]] = hashed) -> list[float]:
    """Mean of the attributes' normalised embeddings."""
    vectors = [vector(description(a)) for a in attributes]
    return [sum(column) / len(vectors) for column in zip(*vectors, strict=True)]


def mean_embedding(rows: DataFrame, key: str) -> DataFrame:
    """(key, bucket, value): query_embedding for many queries at once, of rows(key, vec, n2): of each key the mean of its rows' normalised vectors, non-zero places alone."""
    own = rows.where("n2 > 0").select(key, "vec", F.sqrt(F.col("n2").cast("double")).alias("length"))
    counts = own.groupBy(F.col(key).alias("of")).agg(F.count(F.lit(1)).alias("n"))
    sums = own.select(key, "length", F.explode("vec").alias("bucket", "times")).groupBy(key, "bucket").agg(F.sum(F.col("times") / F.col("length")).alias("total"))
    return sums.join(counts, F.col(key).eqNullSafe(F.col("of"))).select(key, "bucket", (F.col("total") / F.col("n")).alias("value"))


def doc_distance(query: Sequence[float]) -> Column:
    """Least distance of a document's summary vectors from the query's."""
    return F.array_min(F.zip_with("vecs", "n2s", lambda v, n: distance_to(v, n, query)))


def retrieve_docs(docs: DataFrame, query: Sequence[float], tau: float) -> DataFrame:
    """Documents within tau of the query: a filter of the scan, the query being a constant."""
    return docs.withColumn("doc_dist", doc_distance(query)).where(F.col("doc_dist") <= tau)


def refine_docs(docs: DataFrame, tau: float) -> DataFrame:
    return docs.where(F.col("doc_dist") <= tau)


def sample_docs(docs: DataFrame, rate: float = 0.05, seed: str = "sample", least: int = 5) -> DataFrame:
    """Documents whose md5 rank is below the rate, or one of the `least` least; and the `least` nearest the query, so that a small table is met.

    A threshold on the rank, so nothing is counted or sorted but the few of the least ranks and distances.
    """
    rank = md5_rank(F.col("doc_key"), seed)
    parts = docs.where(rank < rate).unionByName(docs.orderBy(rank, "doc_key").limit(least))
    if "doc_dist" in docs.columns:
        parts = parts.unionByName(docs.orderBy("doc_dist", "doc_key").limit(least))
    return parts.dropDuplicates(["doc_key"])


def full_texts(segments: DataFrame) -> DataFrame:
    """(doc_key, text, n_tokens) of whole documents, from all their segments in order."""
    ordered = F.array_sort(F.collect_list(F.struct("seg_no", "text")))
    return segments.groupBy("doc_key").agg(F.array_join(F.transform(ordered, lambda x: x["text"]), "\n").alias("text"), F.sum("n_tokens").alias("n_tokens"))


def shown(attributes: Sequence[Attribute]) -> Callable[[Column], Column]:
    """Whether a segment holds some attribute; `attributes` are these."""
    holds = lambda text: reduce(lambda a, b: a | b, [finds(text, a) for a in attributes])
    holds.attributes = tuple(attributes)
    return holds


def sampled_texts(index: TwoLevelIndex, sample: DataFrame, attributes: Sequence[Attribute] = ()) -> DataFrame:
    """full_texts of the sample's documents; from their own rows, where segments lie there, so that no other document's are made. With attributes, segments
    that hold none of them may lack in the text, as a rule finds nothing in them; the tokens are the whole document's."""
    if index.parts is None:
        return full_texts((index.segments if index.texts is None else index.texts).join(sample, "doc_key", "left_semi"))
    own = index.parts(sample, shown(attributes)) if attributes else index.parts(sample)
    return own.select("doc_key", F.array_join("parts", "\n").alias("text"), "n_tokens")


def analyse(segments: DataFrame, sample: DataFrame, attributes: Sequence[Attribute]) -> DataFrame:
    """Every segment of the sampled documents, read in full: (doc_key, seg_no, n_tokens, vec, has_<attribute> ...)."""
    own = segments.join(sample.select("doc_key", "doc_dist"), "doc_key")
    return own.select("doc_key", "doc_dist", "seg_no", "n_tokens", "vec", "n2", *[finds(F.col("text"), a).alias(f"has_{a.name}") for a in attributes])


def synthesise_evidence(a: Attribute, n: int = 20, generator: Callable[[Attribute, int], list[str]] | None = None) -> list[str]:
    """Passages made up for an attribute that no sampled document holds; a generator may be a model."""
    if generator is not None:
        return generator(a, n)
    frames = ("The {0} is given as {1}.", "Its {0}: {1}.", "{0} on record, {1}.", "We read that the {0} amounts to {1}.")
    return [frames[i % 4].format(description(a), i) for i in range(n)]


def fit_tau(relevant: Iterable[float], margin: float = MARGIN, tau0: float = TAU0) -> float:
    """Largest distance of a relevant sampled document, and a margin; the permissive start where none is relevant."""
    found = list(relevant)
    return min(tau0, max(found) + margin) if found else tau0


def fit_gamma(vectors: Sequence[Sequence[float]], margin: float = MARGIN, block: int = 512) -> float:
    """Diameter of an attribute's evidence, and a margin."""
    x, widest = np.asarray(vectors, float), 0.0
    for at in range(0, len(x), block):
        part = x[at : at + block]
        square = (part**2).sum(1)[:, None] + (x**2).sum(1)[None] - 2 * part @ x.T
        widest = max(widest, float(np.sqrt(np.maximum(square, 0)).max()))
    return widest + margin


def fit_gamma_cluster(vectors: Sequence[Sequence[float]], centres: Sequence[Sequence[float]], margin: float = MARGIN) -> float:
    """Extension: the largest distance of evidence from its own centre, and a margin."""
    x, c = np.asarray(vectors, float), np.asarray(centres, float)
    return float(np.sqrt(((x[:, None] - c[None]) ** 2).sum(2)).min(1).max()) + margin


def fit_probes(
    index: TwoLevelIndex, attributes: Sequence[Attribute], rate: float = 0.05, k: int = 3, probes: str = "evidence", margin: float = MARGIN, tau0: float = TAU0, seed: str = "sample", synthetic: int = 20,
    gamma_mode: str = "diameter", required: str | None = None, generator: Callable[[Attribute, int], list[str]] | None = None, least: int = 10, fixed_gamma: float = 1.1, least_evidence: int = 5,
) -> Probes:
    """Sample the documents a permissive search finds, read them in full, and fit probes and radii.

    A sampled document is relevant if it holds any attribute (or the `required` one). All evidence of the sample counts: tau is an
    aggregate, and the driver gets each distinct vector of an attribute's evidence once, with the number of its segments. probes="description" is free
    of evidence: no sample, the description's own vector and `fixed_gamma` for every attribute, and no radius at the document level. Evidence of fewer than
    `least_evidence` segments says little of how far an attribute's wordings lie apart: synthesised passages join it, an extension. Where there is none,
    these passages alone say nothing of it: the radius is then as permissive as at the document level, and no wording is out of reach.
    """
    query, d = query_embedding(attributes, index.vector), index.dimensions
    if probes == "description":
        return Probes(query, {a.name: [index.vector(description(a))] for a in attributes}, Thresholds(math.inf, {a.name: fixed_gamma for a in attributes}))
    # Distances of documents are asked for several times, and written once.
    ranked = cut(index.docs.select("doc_key", doc_distance(query).alias("doc_dist")), "ranked")
    found = refine_docs(ranked, tau0)
    sample = cut(sample_docs(found, rate, seed, least).select("doc_key", "doc_dist"), "sampled")
    own = index.segments if index.texts is None else batches.embedded(index.texts.join(sample.select("doc_key"), "doc_key", "left_semi"), "text")
    rows = cut(analyse(own, sample, attributes), "analysed")
    held = rows.where(" or ".join(f"has_{a.name}" for a in attributes))
    relevant = held.where(f"has_{required}") if required else held
    farthest = relevant.agg(F.max("doc_dist")).first()[0]
    names = F.array_compact(F.array(*[F.when(F.col(f"has_{a.name}"), F.lit(a.name)) for a in attributes]))
    evidence = held.join(relevant.select("doc_key").distinct(), "doc_key", "left_semi").select(F.explode(names).alias("name"), F.array_sort(F.map_entries("vec")).alias("entries"))
    vectors: dict[str, list] = {a.name: [] for a in attributes}
    for r in evidence.groupBy("name", "entries").agg(F.count(F.lit(1)).alias("n")).orderBy("name", "entries").collect():
        vectors[r.name].append((unit({e["key"]: e["value"] for e in r.entries}, d), r.n))
    total = rows.agg(F.coalesce(F.sum("n_tokens"), F.lit(0)).alias("t"), F.count_distinct("doc_key").alias("n")).first()
    thresholds, centres, sizes = Thresholds(fit_tau([] if farthest is None else [farthest], margin, tau0)), {}, {}
    for a in attributes:
        own, counts = [v for v, _ in vectors[a.name]], [n for _, n in vectors[a.name]]
        sizes[a.name] = sum(counts)
        if probes == "synthetic" or sizes[a.name] < least_evidence:
            made = [index.vector(t) for t in synthesise_evidence(a, synthetic, generator)]
            own, counts = (made, [1] * len(made)) if probes == "synthetic" else (own + made, counts + [1] * len(made))
        centres[a.name] = kmeans_centres(own, k, counts=counts)
        thresholds.gamma[a.name] = fit_gamma(own, margin) if gamma_mode == "diameter" else fit_gamma_cluster(own, centres[a.name], margin)
        if probes == "evidence" and not sizes[a.name]:
            thresholds.gamma[a.name] = max(thresholds.gamma[a.name], tau0)
    return Probes(query, centres, thresholds, sizes, int(total["n"]), int(total["t"]), sample.select("doc_key"), ranked)


def near_any(centres: Sequence[Sequence[float]], gamma: float) -> Column:
    """A segment within gamma of any centre."""
    return F.array_min(F.array(*[distance_to(F.col("vec"), F.col("n2"), c) for c in centres])) <= gamma


def retrieve(index: TwoLevelIndex, attributes: Sequence[Attribute], probes: Probes, two_level: bool = True, search: str = "scan") -> DataFrame:
    """One row a document: cost_<a>, the tokens of the segments near the attribute's evidence, and text_<a>, these segments in order.

    Only segments within a radius meet the refined documents, and `search` says how they are found (TwoLevelIndex.reached). A segment counts once however many centres
    it is near. One aggregation by doc_key; only segments near some attribute are shuffled for it. Documents of the refined set without such a segment are there, with no cost.
    """
    ranked = index.docs.withColumn("doc_dist", doc_distance(probes.query)) if probes.ranked is None else probes.ranked
    docs = refine_docs(ranked, probes.thresholds.tau) if two_level else index.docs
    hits = near_segments(index, attributes, probes, docs if two_level else None, search)
    return gathered(hits, docs.select("doc_key"), [a.name for a in attributes])


def near_segments(index: TwoLevelIndex, attributes: Sequence[Attribute], probes: Probes, docs: DataFrame | None = None, search: str = "scan") -> DataFrame:
    """(doc_key, seg_no, text, n_tokens, near_<a> ...): segments of docs within the radius of some attribute's evidence."""
    asked = [(c, probes.thresholds.gamma[a.name]) for a in attributes for c in probes.centres[a.name]]
    radii = [(a.name, probes.centres[a.name], probes.thresholds.gamma[a.name]) for a in attributes]
    hits = batches.near(index.reached(asked, search), radii) if index.texts is None or search != "scan" else batches.near_texts(index.texts, radii)
    return hits if docs is None else hits.join(docs.select("doc_key"), "doc_key", "left_semi").select(hits.columns)


def gathered(hits: DataFrame, docs: DataFrame, names: Sequence[str]) -> DataFrame:
    """hits(doc_key, seg_no, text, n_tokens, near_<a> ...) to one row for each of docs(doc_key)."""
    sums = []
    for n in names:
        near = F.col(f"near_{n}")
        ordered = F.array_sort(F.collect_list(F.when(near, F.struct("seg_no", "text"))))
        sums += [F.coalesce(F.sum(F.when(near, F.col("n_tokens"))), F.lit(0)).cast("bigint").alias(f"cost_{n}"), F.array_join(F.transform(ordered, lambda x: x["text"]), "\n").alias(f"text_{n}")]
    found = docs.join(hits.groupBy("doc_key").agg(*sums), "doc_key", "left")
    return found.fillna(0, [f"cost_{n}" for n in names]).fillna("", [f"text_{n}" for n in names])


def retrieve_located(index: TwoLevelIndex, attributes: Sequence[Attribute]) -> DataFrame:
    """Perfect retrieval: the segments that hold the attribute, and no other. Inside a document's row, where its segments lie there: nothing is shuffled."""
    if index.parts is not None:
        made = index.parts(None, shown(attributes))
        for a in attributes:
            hits = F.filter("parts", lambda s: finds(s, a))  # noqa: B023
            made = made.withColumn(f"hits_{a.name}", F.coalesce(hits, F.array().cast("array<string>")))
        cost = lambda hits: F.aggregate(hits, F.lit(0).cast("bigint"), lambda n, s: n + n_tokens(s))
        return made.select("doc_key", *[cost(f"hits_{a.name}").alias(f"cost_{a.name}") for a in attributes], *[F.array_join(f"hits_{a.name}", "\n").alias(f"text_{a.name}") for a in attributes])
    flags = index.segments.withColumns({f"near_{a.name}": finds(F.col("text"), a) for a in attributes})
    hits = flags.where(" or ".join(f"near_{a.name}" for a in attributes)).select("doc_key", "seg_no", "text", "n_tokens", *[f"near_{a.name}" for a in attributes])
    return gathered(hits, index.docs.select("doc_key"), [a.name for a in attributes])


def retrieve_full(index: TwoLevelIndex, attributes: Sequence[Attribute]) -> DataFrame:
    """The whole document for every attribute."""
    flags = index.segments.withColumns({f"near_{a.name}": F.lit(True) for a in attributes}).select("doc_key", "seg_no", "text", "n_tokens", *[f"near_{a.name}" for a in attributes])
    return gathered(flags, index.docs.select("doc_key"), [a.name for a in attributes])


def retrieve_topk(index: TwoLevelIndex, attributes: Sequence[Attribute], k: int) -> DataFrame:
    """For each document the k segments nearest each attribute's description."""
    rows = index.segments
    for a in attributes:
        probe = index.vector(description(a))
        rows = rows.withColumn(f"d_{a.name}", distance_to(F.col("vec"), F.col("n2"), probe))
    top = rows.groupBy("doc_key").agg(*[F.transform(F.slice(F.array_sort(F.collect_list(F.struct(f"d_{a.name}", "seg_no"))), 1, k), lambda x: x["seg_no"]).alias(f"top_{a.name}") for a in attributes])
    flags = index.segments.join(top, "doc_key").withColumns({f"near_{a.name}": F.array_contains(f"top_{a.name}", F.col("seg_no")) for a in attributes})
    return gathered(flags.select("doc_key", "seg_no", "text", "n_tokens", *[f"near_{a.name}" for a in attributes]), index.docs.select("doc_key"), [a.name for a in attributes])
