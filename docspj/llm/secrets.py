"""Secret scan in DataFrame functions alone: three patterns, and character Markov models for what patterns miss.

Two first-order Markov models over the characters of keys and identifiers, one of random strings and one of ordinary
identifiers, are counted from labelled samples. A run of such characters is secret-like if the logarithm of the ratio of its
likelihoods, and its mean a character, are high enough.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from docspj.llm.common import bounded_sample

#: The base patterns with the least length that a match, or its second group, must have.
KINDS = {
    "assign": (r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6),
    "access": (r"AKIA[A-Z0-9]+", 0, 20),
    "hex": (r"[0-9a-f]+", 0, 24),
}
#: What stands for a pattern in the scan where it gives the same matches of sufficient length and is quicker.
_SCANNED = {"access": r"AKIA[A-Z0-9]{16,}", "hex": r"[0-9a-f]{24,}"}
ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_=-"
_RUN = r"[A-Za-z0-9+/_=-]{20,}"


@dataclass(frozen=True)
class MarkovRatio:
    """weights: log-likelihood ratio of each pair of ALPHABET's characters, row by row."""

    weights: tuple[float, ...]
    least_mean: float = 0.5
    least_total: float = 12.0


def running(values: Column, start: int, op: Callable[[Column, Column], Column], block: int = 256) -> Column:
    """array<int>: what op makes of start and all values before each place. In blocks, so that growing an array by one copies a block at most."""

    def prefix(xs: Column, first: Column) -> Column:
        state = F.struct(first.alias("at"), F.array().cast("array<int>").alias("out"))
        return F.aggregate(xs, state, lambda s, x: F.struct(op(s["at"], x).alias("at"), F.concat(s["out"], F.array(s["at"])).alias("out")), lambda s: s["out"])

    count = F.ceil(F.size(values) / F.lit(float(block))).cast("int")
    blocks = F.when(count > 0, F.transform(F.sequence(F.lit(0), F.greatest(count, F.lit(1)) - 1), lambda b: F.slice(values, b * block + 1, block))).otherwise(F.array().cast("array<array<int>>"))
    bases = prefix(F.transform(blocks, lambda b: F.aggregate(b, F.lit(start), op)), F.lit(start))
    return F.flatten(F.zip_with(blocks, bases, prefix))


def _spans(text: Column, pattern: str, group: int, least: int, kind: int) -> Column:
    """array(struct(start, kind, end)) of the leftmost, non-overlapping matches whose group is long enough, in code points."""
    regex = F.lit(pattern)
    length = lambda x: F.coalesce(F.char_length(x), F.lit(0))
    zipped = F.arrays_zip(F.split(text, pattern, -1).alias("gap"), F.regexp_extract_all(text, regex, 0).alias("all"), F.regexp_extract_all(text, regex, group).alias("part"))
    sizes = F.transform(zipped, lambda x: F.struct(length(x["gap"]).alias("gap"), length(x["all"]).alias("all"), length(x["part"]).alias("part")))

    def placed(xs: Column) -> Column:
        before = running(F.transform(xs, lambda x: x["gap"] + x["all"]), 0, lambda a, b: a + b)
        spans = F.zip_with(xs, before, lambda x, at: F.struct((at + x["gap"]).alias("start"), F.lit(kind).alias("kind"), (at + x["gap"] + x["all"]).alias("end"), x["part"].alias("part")))
        return F.transform(F.filter(spans, lambda s: s["part"] >= least), lambda s: F.struct(s["start"].alias("start"), s["kind"].alias("kind"), s["end"].alias("end")))

    none = F.array().cast("array<struct<start:int,kind:int,end:int>>")
    return F.when(F.coalesce(text.rlike(pattern), F.lit(False)), once(sizes, placed)).otherwise(none)


def once(value: Column, body: Callable[[Column], Column]) -> Column:
    """body of a value that is computed once, however often body names it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def untouched(base: Column, runs: Column, kind: int) -> Column:
    """Those of the runs, spans of the given kind, that no base span touches: a pass over both in order of their starts, each way."""
    never = (1 << 31) - 1

    def of(spans: Column) -> Column:
        reach = running(F.transform(spans, lambda s: F.when(s["kind"] == kind, 0).otherwise(s["end"])), 0, lambda a, b: F.greatest(a, b))
        following = F.reverse(running(F.reverse(F.transform(spans, lambda s: F.when(s["kind"] == kind, never).otherwise(s["start"]))), never, lambda a, b: F.least(a, b)))
        zipped = F.arrays_zip(spans.alias("s"), reach.alias("reach"), following.alias("next"))
        free = F.filter(zipped, lambda x: (x["s"]["kind"] == kind) & (x["reach"] <= x["s"]["start"]) & (x["next"] >= x["s"]["end"]))
        return F.transform(free, lambda x: x["s"])

    return F.when((F.size(base) == 0) | (F.size(runs) == 0), runs).otherwise(once(F.array_sort(F.concat(base, runs)), of))


def labelled_samples(docs: DataFrame, documents: int = 300, strings: int = 1500, seed: int = 3) -> DataFrame:
    """(sample, is_secret): digests written in base64, in capital and in small letters; words, capitals, compounds and numbers of documents.

    Bounded: `strings` digests, and the words of `documents` documents of least seeded hash.
    """
    spark = docs.sparkSession
    digest = F.sha2(F.concat(F.lit(f"{seed}:"), F.col("id").cast("string")), 256)
    alone = F.regexp_replace(F.base64(F.unhex(digest)), "[+/=]", "")
    random = spark.range(strings).select(F.explode(F.array(F.base64(F.unhex(digest)), alone, F.upper(digest))).alias("sample"), F.lit(True).alias("is_secret"))
    ids = bounded_sample(docs.select("doc_id").where("doc_id is not null and text is not null"), "doc_id", documents, seed).distinct()
    chosen = docs.select("doc_id", "text").join(F.broadcast(ids), "doc_id", "left_semi").where("text is not null")
    words = chosen.select(F.regexp_extract_all("text", F.lit(r"[A-Za-z]{3,}"), 0).alias("words"))
    join = lambda sep: F.transform(F.sequence(F.lit(1), F.size("words") - 1), lambda i: F.concat_ws(sep, F.element_at("words", i), F.element_at("words", i + 1)))
    ordinary = words.where("size(words) > 1").select(F.explode(F.concat("words", F.transform("words", lambda w: F.upper(w)), join("_"), join("-"), F.transform(join(" "), lambda w: F.regexp_replace(F.initcap(w), " ", "")))).alias("sample"), F.lit(False).alias("is_secret"))
    numbers = spark.range(strings * 4).select(F.regexp_replace(F.sha2(F.concat(F.lit(f"n{seed}:"), F.col("id").cast("string")), 256), "[a-f]", "").alias("sample"), F.lit(False).alias("is_secret"))
    return random.unionByName(ordinary).unionByName(numbers)


def train_markov(samples: DataFrame, smoothing: float = 0.5, **limits: float) -> MarkovRatio:
    """Models from samples(sample, is_secret). The driver gets one count for a label and pair of characters of ALPHABET, 2 x 67 x 67 at most."""
    chars = F.split(F.regexp_replace("sample", f"[^{ALPHABET}]", ""), "")
    pairs = F.transform(F.sequence(F.lit(1), F.size("chars") - 1), lambda i: F.concat(F.element_at("chars", i), F.element_at("chars", i + 1)))
    split = samples.where("sample is not null and is_secret is not null").select(F.filter(chars, lambda c: c != "").alias("chars"), "is_secret").where("size(chars) > 1")
    rows = split.select(F.explode(pairs).alias("pair"), "is_secret").groupBy("pair", "is_secret").count().collect()
    size = len(ALPHABET)
    counts = {True: [[smoothing] * size for _ in ALPHABET], False: [[smoothing] * size for _ in ALPHABET]}
    for r in rows:
        counts[r.is_secret][ALPHABET.index(r.pair[0])][ALPHABET.index(r.pair[1])] += r[2]
    chance = {k: [[n / sum(row) for n in row] for row in table] for k, table in counts.items()}
    weights = [round(math.log(chance[True][a][b] / chance[False][a][b]), 4) for a in range(size) for b in range(size)]
    return MarkovRatio(tuple(weights), **limits)


def log_ratio(run: Column, model: MarkovRatio) -> Column:
    """Sum of the weights of a run's pairs of neighbouring characters."""
    table, size = F.lit(list(model.weights)), len(ALPHABET)
    codes = F.transform(F.filter(F.split(run, ""), lambda c: c != ""), lambda c: F.instr(F.lit(ALPHABET), c))
    state = F.struct(F.lit(0).alias("last"), F.lit(0.0).alias("sum"))
    return F.aggregate(
        codes, state,
        lambda s, c: F.struct(c.alias("last"), (s["sum"] + F.when(s["last"] > 0, F.element_at(table, (s["last"] - 1) * size + c)).otherwise(0.0)).alias("sum")),
        lambda s: s["sum"],
    )


def scan_secrets(docs: DataFrame, model: MarkovRatio) -> DataFrame:
    """(doc_id, base, added) of each row of docs(doc_id, text): arrays of (start, kind, end, value) in code points, end exclusive.

    kind is a place in KINDS, or one past it for what the models find; found runs that touch a base span are left out. A null or empty text has none.
    Repeated rows are each scanned. Other columns are ignored.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    spans = [_spans(text, _SCANNED.get(name, pattern), group, least, k) for k, (name, (pattern, group, least)) in enumerate(KINDS.items())]
    rows = docs.select("doc_id", text.alias("text"), F.array_sort(F.concat(*spans)).alias("base"), _spans(text, _RUN, 0, 20, len(KINDS)).alias("runs"))
    cut = lambda s: F.substring(F.col("text"), s["start"] + 1, s["end"] - s["start"])
    free = untouched(F.col("base"), F.col("runs"), len(KINDS))
    rated = F.transform(free, lambda r: F.struct(r["start"].alias("start"), r["kind"].alias("kind"), r["end"].alias("end"), log_ratio(cut(r), model).alias("ratio")))
    secret = F.filter(rated, lambda r: (r["ratio"] >= model.least_total) & (r["ratio"] >= model.least_mean * (r["end"] - r["start"] - 1)))
    valued = lambda spans: F.transform(spans, lambda s: F.struct(s["start"].alias("start"), s["kind"].alias("kind"), s["end"].alias("end"), cut(s).alias("value")))
    return rows.select("doc_id", valued(F.col("base")).alias("base"), valued(F.when(F.size("runs") > 0, secret).otherwise(F.array().cast("array<struct<start:int,kind:int,end:int,ratio:double>>"))).alias("added"))


def span_text(spans: Column) -> Column:
    """kind:start:end of each span, comma-joined."""
    names = F.array(*[F.lit(k) for k in (*KINDS, "markov")])
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.element_at(names, s["kind"] + 1), s["start"].cast("string"), s["end"].cast("string"))), ",")
