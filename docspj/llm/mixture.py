"""Mixing sources to target weights by Efraimidis-Spirakis sampling.

A document's key is an exponential draw, from a hash of its id, over its quality weight. A source whose target is e times its
size and a rest gives e whole epochs, and for the rest its documents of least keys up to the budget,
and the one document more that comes nearest to what these leave of it. Keys are dealt into
buckets by size; sums by bucket say which bucket the budget ends in, twice more that bucket is dealt into finer ones, and only what
lies in the last is sorted and prefix-summed: a part of the source that its own size divided by millions gives. Then a source is a cut
key and a closing document, and whether a row is taken is a comparison with these: no window sees a text.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from docspj.llm.common import scratch, word_count


def text_quality(text: Column) -> Column:
    """Quality weight of a text from the text alone: its share of letters and blanks, 0.25 at least."""
    kept = F.char_length(F.regexp_replace(text, r"[^\p{L} ]+", ""))
    return F.coalesce(F.greatest(F.lit(0.25), F.try_divide(kept, F.char_length(text))), F.lit(0.25))


def targets(sizes: dict[str | None, int], weights: Sequence[float] = (5, 2, 1), share: float = 1.5, most_epochs: float = 2.0) -> dict[str | None, float]:
    """Words wanted of each source: share of all words by weight, capped at most_epochs of a source, the excess dealt again by weight."""
    names = sorted((s for s in sizes if s is not None)) + [None] * (None in sizes)
    weight = {s: float(weights[i % len(weights)]) for i, s in enumerate(names)}
    caps = {s: most_epochs * sizes[s] for s in names}
    left, open_ = min(share * sum(sizes.values()), sum(caps.values())), set(names)
    got: dict[str | None, float] = {}
    while open_:
        level = left / sum(weight[s] for s in open_)
        full = {s for s in open_ if weight[s] * level > caps[s]}
        if not full:
            return got | {s: weight[s] * level for s in open_}
        got |= {s: caps[s] for s in full}
        left -= sum(caps[s] for s in full)
        open_ -= full
    return got


#: Buckets a doubling of the key, and how many finer ones each is dealt into at each of two steps.
_COARSE, _FINER = 64, 1024


def _unit(seed: int) -> Column:
    return (F.shiftrightunsigned(F.xxhash64(F.lit(seed), F.col("doc_id").cast("string")), 11) + F.lit(0.5)) / float(1 << 53)


def sampling_key(seed: int) -> Column:
    """The Efraimidis-Spirakis key of a row of docs(doc_id, text), an exponential draw over the quality weight: least keys come first."""
    return -F.log(_unit(seed)) / text_quality(F.col("text"))


def _bucket(step: int) -> Column:
    return F.floor(F.log2("key") * (_COARSE * _FINER**step)).cast("long")


def _plans(sized: DataFrame, weights: Sequence[float], share: float, most_epochs: float, most_sources: int) -> DataFrame:
    """A row a source of sized(doc_id, source, size, key): of, source_size, target, epochs, end, cut, closing.

    The fractional epoch takes rows in buckets before `end`, in it those up to the struct `cut` of key and id, and the struct `closing`.
    """
    spark = sized.sparkSession
    sizes = {r[0]: r[1] for r in sized.groupBy("source").agg(F.sum("size")).limit(most_sources + 1).collect()}
    if len(sizes) > most_sources:
        raise ValueError(f"more than {most_sources} sources")
    plan = []
    for s, wanted in targets(sizes, weights, share, most_epochs).items():
        epochs = int(wanted // sizes[s]) if sizes[s] else 0
        plan.append((s, sizes[s], float(wanted), epochs, float(wanted - epochs * sizes[s])))
    plan = spark.createDataFrame(plan, "of string, source_size long, target double, epochs int, rest double")
    # Which bucket the budget ends in, and the words before it; then the same within it. A budget of nothing ends nowhere.
    edges = plan.where("rest > 0").select("of", "rest", F.lit(None).cast("long").alias("end"), F.lit(0).cast("long").alias("before"))
    for step in range(3):
        inside = sized.join(F.broadcast(edges), F.col("source").eqNullSafe(F.col("of")))
        if step:
            inside = inside.where(_bucket(step - 1) == F.col("end"))
        held = inside.groupBy("of", "rest", "before", _bucket(step).alias("bucket")).agg(F.sum("size").alias("held"))
        upto = held.withColumn("upto", F.col("before") + F.sum("held").over(Window.partitionBy("of").orderBy("bucket").rowsBetween(Window.unboundedPreceding, Window.currentRow)))
        last = F.min_by(F.struct("bucket", (F.col("upto") - F.col("held")).alias("start")), "bucket").alias("last")
        edges = scratch(upto.where("upto >= rest").groupBy("of", "rest").agg(last).select("of", "rest", F.col("last.bucket").alias("end"), F.col("last.start").alias("before")), "edges")
    spot = F.struct("key", "doc_id")
    # Rows of one key and id, repeated rows, are taken together.
    inside = sized.join(F.broadcast(edges), F.col("source").eqNullSafe(F.col("of"))).where(_bucket(2) == F.col("end"))
    inside = inside.groupBy("of", "rest", "before", spot.alias("spot")).agg(F.sum("size").alias("size"))
    upto = inside.withColumn("upto", F.col("before") + F.sum("size").over(Window.partitionBy("of").orderBy("spot").rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    fits = F.col("upto") <= F.col("rest")
    cuts = upto.groupBy("of").agg(F.max(F.when(fits, F.col("spot"))).alias("cut"), F.max(F.when(fits, F.col("upto"))).alias("taken"))
    cuts = scratch(edges.join(cuts.withColumnRenamed("of", "from"), F.col("of").eqNullSafe(F.col("from"))).select("of", "end", "cut", (F.col("rest") - F.coalesce("taken", "before")).alias("gap")), "cuts")
    # What whole documents leave of a budget goes to the one document of the rest that comes nearest to it.
    off = F.abs(F.col("gap") - F.col("size"))
    left = sized.where("size > 0").join(F.broadcast(cuts), F.col("source").eqNullSafe(F.col("of"))).where(~_within())
    closing = left.groupBy("of", "gap", spot.alias("spot")).agg(F.sum("size").alias("size")).where(off < F.col("gap")).groupBy("of").agg(F.min_by("spot", F.struct(off, "spot")).alias("closing"))
    parts = plan.join(cuts.select(F.col("of").alias("a"), "end", "cut"), F.col("of").eqNullSafe(F.col("a")), "left").join(closing.select(F.col("of").alias("b"), "closing"), F.col("of").eqNullSafe(F.col("b")), "left")
    return scratch(parts.select("of", "source_size", "target", "epochs", "end", "cut", "closing"), "plan")


def _within() -> Column:
    """Whether a row of a key and id lies before the cut of its source."""
    spot = F.struct("key", "doc_id")
    return F.coalesce((_bucket(2) < F.col("end")) | ((_bucket(2) == F.col("end")) & (spot <= F.col("cut"))), F.lit(False))


def _copies() -> Column:
    closes = F.coalesce(F.struct("key", "doc_id") == F.col("closing"), F.lit(False))
    return F.col("epochs") + (_within() | closes).cast("int")


def mix_sources(docs: DataFrame, weights: Sequence[float] = (5, 2, 1), share: float = 1.5, most_epochs: float = 2.0, seed: int = 1, most_sources: int = 100_000) -> DataFrame:
    """(doc_id, source, size, source_size, target, copies, taken) of every row of docs(doc_id, text, source).

    copies: how often the mix takes the document; taken = copies x size. A null or empty text has size 0 and is taken in whole
    epochs and, its key allowing, in the fractional one. A null source is a source, the last in order. Rows that repeat an id in a source share its
    draw, and those of one weight are taken together; ties of key go by id. Reruns agree: keys are hashes. The driver gets one sum a source, and refuses more
    than `most_sources`.
    """
    sized = scratch(docs.select("doc_id", "source", word_count(F.col("text")).alias("size"), sampling_key(seed).alias("key")), "sizes")
    plan = _plans(sized, weights, share, most_epochs, most_sources)
    chosen = sized.join(F.broadcast(plan), F.col("source").eqNullSafe(F.col("of"))).withColumn("copies", _copies())
    return chosen.select("doc_id", "source", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"))


def mixed_rows(docs: DataFrame, weights: Sequence[float] = (5, 2, 1), share: float = 1.5, most_epochs: float = 2.0, seed: int = 1, most_sources: int = 100_000) -> DataFrame:
    """The mix itself: rows of docs with all their columns, each as often as the mix takes it."""
    sized = scratch(docs.select("doc_id", "source", word_count(F.col("text")).alias("size"), sampling_key(seed).alias("key")), "sizes")
    plan = _plans(sized, weights, share, most_epochs, most_sources)
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), "doc_id", "source", sampling_key(seed).alias("key"))
    taken = rows.join(F.broadcast(plan), F.col("source").eqNullSafe(F.col("of"))).withColumn("copies", _copies()).where("copies > 0")
    return taken.select("row", F.explode(F.array_repeat(F.lit(0), F.col("copies")))).select("row.*")
