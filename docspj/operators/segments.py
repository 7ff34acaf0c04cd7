"""Segments and summaries of documents, each made inside the document's row: no shuffle."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from docspj.functions.text import DIMENSIONS, distance, embed, n_tokens, norm2, sentences, words

MODES = ("previous", "running", "percentile")


def _let(value: Column, body) -> Column:
    return F.element_at(F.transform(F.array(value), body), 1)


def _described(text: Column, d: int) -> Column:
    """array(struct(text, tokens, vec, n2)) of a text's sentences."""
    with_vector = lambda s: _let(embed(s, d), lambda v: F.struct(s.alias("text"), n_tokens(s).alias("tokens"), v.alias("vec"), norm2(v).alias("n2")))
    return F.transform(sentences(text), with_vector)


def _sum_maps(a: Column, b: Column) -> Column:
    return F.map_zip_with(a, b, lambda k, x, y: F.coalesce(x, F.lit(0)) + F.coalesce(y, F.lit(0)))


def segment(docs: DataFrame, mode: str = "previous", sim_threshold: float = 0.25, max_tokens: int = 200, q: float = 0.9, d: int = DIMENSIONS) -> DataFrame:
    """(corpus, doc_key, seg_no, text, n_tokens, first_sent, last_sent): runs of neighbouring sentences of like meaning.

    previous: a sentence joins the segment if its cosine with the sentence before is at least sim_threshold. running: with the segment
    so far. percentile: a cut falls where a neighbours' distance is above the document's q-th percentile. A segment of max_tokens is closed.
    """
    if mode not in MODES:
        raise ValueError(mode)
    far = (2 - 2 * sim_threshold) ** 0.5
    base = docs.select("corpus", "doc_key", _described(F.col("text"), d).alias("sents"))
    gap = lambda i: distance(F.element_at("sents", i)["vec"], F.element_at("sents", i + 1)["vec"], F.element_at("sents", i)["n2"], F.element_at("sents", i + 1)["n2"])
    limit = F.lit(far)
    if mode == "percentile":
        gaps = F.when(F.size("sents") > 1, F.array_sort(F.transform(F.sequence(F.lit(1), F.size("sents") - 1), gap))).otherwise(F.array(F.lit(far)))
        base = base.withColumn("limit", _let(gaps, lambda g: F.element_at(g, F.greatest(F.lit(1), F.ceil(F.size(g) * q).cast("int")))))
        limit = F.col("limit")
    empty = F.struct(
        F.lit(-1).alias("n"), F.lit(0).alias("tokens"), F.create_map().cast("map<int,int>").alias("vec"), F.lit(0).cast("bigint").alias("n2"), F.array().cast("array<int>").alias("seg")
    )

    def step(s: Column, x: Column) -> Column:
        near = distance(s["vec"], x["vec"], s["n2"], x["n2"]) <= limit
        joins = (s["n"] >= 0) & near & (s["tokens"] + x["tokens"] <= max_tokens)
        number = F.when(joins, s["n"]).otherwise(s["n"] + 1)
        vec = F.when(joins, _sum_maps(s["vec"], x["vec"])).otherwise(x["vec"]) if mode == "running" else x["vec"]
        return _let(vec, lambda v: F.struct(
            number.alias("n"), F.when(joins, s["tokens"] + x["tokens"]).otherwise(x["tokens"]).alias("tokens"), v.alias("vec"), (norm2(v) if mode == "running" else x["n2"]).alias("n2"), F.concat(s["seg"], F.array(number)).alias("seg")
        ))

    numbered = base.withColumn("seg", F.aggregate("sents", empty, step, lambda s: s["seg"]))
    # A segment begins where the number changes and ends before the next one begins: each is one slice of the sentences.
    begins = F.filter(F.sequence(F.lit(0), F.size("sents") - 1), lambda i: (i == 0) | (F.get("seg", i) != F.get("seg", i - 1)))
    bounds = numbered.where("size(sents) > 0").withColumn("begins", F.concat(begins, F.array(F.size("sents"))))
    slices = F.transform(F.slice("begins", 1, F.size("begins") - 1), lambda b, i: F.struct(b.alias("first"), F.transform(F.slice("sents", b + 1, F.get("begins", i + 1) - b), lambda x: x["text"]).alias("texts")))
    rows = bounds.select("corpus", "doc_key", F.posexplode(slices).alias("seg_no", "own"))
    text = F.array_join("own.texts", " ")
    return rows.select("corpus", "doc_key", "seg_no", text.alias("text"), n_tokens(text).alias("n_tokens"), F.col("own.first").alias("first_sent"), (F.col("own.first") + F.size("own.texts") - 1).alias("last_sent"))


def segment_fixed(docs: DataFrame, tokens: int = 100, overlap: int = 0) -> DataFrame:
    """Windows of so many tokens, each starting tokens - overlap after the one before."""
    words_ = F.regexp_extract_all("text", F.lit(r"\S+"), 0)
    base = docs.select("corpus", "doc_key", words_.alias("w")).where("size(w) > 0")
    step = max(1, tokens - overlap)
    rows = base.select("corpus", "doc_key", "w", F.posexplode(F.sequence(F.lit(1), F.size("w"), F.lit(step))).alias("seg_no", "at"))
    piece = F.slice("w", F.col("at"), F.lit(tokens))
    return rows.select("corpus", "doc_key", "seg_no", F.array_join(piece, " ").alias("text"), F.size(piece).alias("n_tokens"), F.lit(None).cast("int").alias("first_sent"), F.lit(None).cast("int").alias("last_sent"))


def segment_located(docs: DataFrame) -> DataFrame:
    """One segment a line: for documents whose markup already parts them."""
    rows = docs.select("corpus", "doc_key", F.posexplode(F.split("text", r"\n")).alias("seg_no", "text"))
    return rows.select("corpus", "doc_key", "seg_no", "text", n_tokens(F.col("text")).alias("n_tokens"), F.col("seg_no").alias("first_sent"), F.col("seg_no").alias("last_sent"))


def summarise(docs: DataFrame, mode: str = "frequency", r: int = 3) -> DataFrame:
    """(corpus, doc_key, sentences, summary): key sentences of each document.

    frequency: the r sentences whose words are the most frequent in the document on average, in order. lead: the opening sentence. multi: as
    frequency, each sentence to be embedded by itself.
    """
    cut = docs.select("corpus", "doc_key", sentences(F.col("text")).alias("s"))
    if mode == "lead":
        return cut.select("corpus", "doc_key", F.slice("s", 1, 1).alias("sentences"), F.coalesce(F.try_element_at("s", F.lit(1)), F.lit("")).alias("summary"))
    scored = cut.select("corpus", "doc_key", "s", F.transform("s", words).alias("w")).select("corpus", "doc_key", "s", "w", F.flatten("w").alias("every"))
    counts = F.map_from_entries(F.transform(F.array_distinct("every"), lambda x: F.struct(x, F.size(F.filter("every", lambda y: y == x)))))
    scored = scored.withColumn("tf", counts)
    score = lambda ws: F.when(F.size(ws) > 0, F.aggregate(ws, F.lit(0.0), lambda a, w: a + F.element_at("tf", w)) / F.size(ws)).otherwise(0.0)
    ranked = F.slice(F.array_sort(F.transform("w", lambda ws, i: F.struct((-score(ws)).alias("less"), i.alias("i")))), 1, r)
    best = F.transform(F.array_sort(F.transform(ranked, lambda x: x["i"])), lambda i: F.element_at("s", i + 1))
    return scored.select("corpus", "doc_key", best.alias("sentences")).withColumn("summary", F.array_join("sentences", " "))


def segment_by_window(docs: DataFrame, sim_threshold: float = 0.25, d: int = DIMENSIONS) -> DataFrame:
    """The cuts of mode `previous` (without a limit of tokens) as windows over sentence rows: the same answer, for checks in SQL."""
    rows = docs.select("doc_key", F.posexplode(sentences(F.col("text"))).alias("pos", "s")).withColumn("vec", embed(F.col("s"), d)).withColumn("n2", norm2(F.col("vec")))
    w = Window.partitionBy("doc_key").orderBy("pos")
    gap = distance(F.lag("vec").over(w), F.col("vec"), F.lag("n2").over(w), F.col("n2"))
    cut = F.when(F.col("pos") == 0, 0).otherwise((gap > (2 - 2 * sim_threshold) ** 0.5).cast("int"))
    return rows.withColumn("cut", cut).withColumn("seg_no", F.sum("cut").over(w.rowsBetween(Window.unboundedPreceding, 0))).select("doc_key", "pos", "cut", "seg_no")
