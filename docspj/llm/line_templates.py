"""Line dedup by a log-template tree: recurring templates across documents are dropped.

A line's words that hold a digit are variable fields. The tree has fixed depth: the number of words, then the leading words. Below it, in a
leaf, a word is constant at its place if enough documents have it there, and else a variable field; a line's template is its constants
and fields. So a template is a function of counts, which all rows share, and not of the order in which a parser met the lines: every
step is an aggregate or a join that many tasks share, a leaf of any size is split among them, and a line that a third of all rows
hold is one row before its words are looked at.

Lines that recur in fewer documents are passages, not boilerplate: chance repeats a long line less than a short one, so the longer a
line, the fewer documents it takes, and one document keeps it.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from docspj.llm.common import scratch

FIELD = "<*>"


def masked(line: Column) -> Column:
    """A line, blanks made single and words with digits made variable."""
    blanks = reduce(lambda a, b: a | b, [F.contains(line, F.lit(b)) for b in ("  ", "\t", "\x0b", "\f", "\r")])
    single = F.when(blanks, F.regexp_replace(line, r"[ \t\x0B\f\r]+", " ")).otherwise(line)
    return F.trim(F.when(single.rlike("[0-9]"), F.regexp_replace(single, r"(?<!\S)[^\s\d]*+\d\S*", FIELD)).otherwise(single))


def word_number(line: Column) -> Column:
    return F.size(F.split(line, " "))


def leaf(line: Column, depth: int) -> Column:
    return F.when(line != "", F.xxhash64(word_number(line), F.substring_index(line, " ", depth)))


def fixed_number(line: Column) -> Column:
    """Words that are no fields."""
    fields = ((F.length(line) - F.length(F.replace(line, F.lit(FIELD), F.lit("")))) / len(FIELD)).cast("int")
    return word_number(line) - F.when(F.contains(line, F.lit(FIELD)), fields).otherwise(0)


def line_templates(lines: DataFrame, least_documents: int, depth: int, similarity: float, least_words: int) -> DataFrame:
    """(leaf, line, template) of distinct lines(leaf, line, documents).

    Lines of fewer than `least_words` words, and those whose constants are under `similarity` of the words that are no fields, are their own template.
    """
    # A line's words carry two hashes of it, not the line itself, which would be shuffled once a word.
    marked_lines = lines.withColumns({"mark": F.xxhash64(F.lit(1), "line"), "mark2": F.xxhash64(F.lit(2), "line")})
    many = marked_lines.where(word_number(F.col("line")) >= least_words)
    words = many.select("leaf", "mark", "mark2", "documents", F.posexplode(F.split("line", " ")).alias("place", "word"))
    common = words.where((F.col("place") >= depth) & (F.col("word") != FIELD)).groupBy("leaf", "place", "word").agg(F.sum("documents").alias("n")).where(F.col("n") >= least_documents).select("leaf", "place", "word", F.lit(True).alias("constant"))
    kept = (F.col("place") < depth) | F.col("constant").isNotNull()
    marked = words.drop("documents").join(common, ["leaf", "place", "word"], "left").select("leaf", "mark", "mark2", F.struct("place", F.when(kept, F.col("word")).otherwise(FIELD).alias("word")).alias("at"))
    made = marked.groupBy("leaf", "mark", "mark2").agg(F.array_join(F.transform(F.array_sort(F.collect_list("at")), lambda x: x["word"]), " ").alias("made"))
    alike = fixed_number(F.col("made")) >= similarity * fixed_number(F.col("line"))
    own = marked_lines.join(made, ["leaf", "mark", "mark2"], "left").withColumn("alike", F.coalesce(alike, F.lit(False)))
    return own.select("leaf", "line", F.when(F.col("alike"), F.col("made")).otherwise(F.col("line")).alias("template"))


def passages_needed(fixed: Column, least_documents: int, long_words: int) -> Column:
    """Documents that a line of so many fixed words must recur in: `least_documents` for none, falling evenly to 2 at `long_words` and beyond."""
    return F.greatest(F.lit(2), F.lit(least_documents) - F.floor(fixed * (least_documents - 2) / long_words).cast("int"))


def repeated_passages(held: DataFrame, least_documents: int, long_words: int) -> DataFrame:
    """(doc_id, key, at) of held(doc_id, key, at, fixed, mark, mark2) lines that enough documents hold, but for those of the document of least id."""
    # Most lines stand once: these go before documents are counted.
    twice = held.groupBy("mark", "mark2").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("mark", "mark2")
    some = scratch(held.join(twice, ["mark", "mark2"], "left_semi"), "repeated")
    found = some.select("mark", "mark2", "doc_id", "key", "fixed").distinct().groupBy("mark", "mark2").agg(F.min("doc_id").alias("first"), F.count(F.lit(1)).alias("documents"), F.max("fixed").alias("fixed"))
    again = found.where(F.col("documents") >= passages_needed(F.col("fixed"), least_documents, long_words)).select("mark", "mark2", "first")
    return some.join(again, ["mark", "mark2"]).where(~F.col("doc_id").eqNullSafe(F.col("first"))).select("doc_id", "key", "at")


def drop_recurring_lines(docs: DataFrame, least_documents: int = 10, depth: int = 3, similarity: float = 0.6, long_words: int = 50, least_words: int = 8) -> DataFrame:
    """(doc_id, n_lines, n_dropped, text) of each row of docs(doc_id, text): the text without lines of templates that `least_documents` documents
    hold; and without lines that fewer documents repeat, from 2 on for `long_words` fixed words or more, which the document of least id keeps.

    Only lines of `least_words` words or more take words that differ for fields; shorter ones must be equal but for words with digits. Lines are cut at
    line feeds; blank lines are never dropped. A null text stays null and has no lines; an empty text is one blank line. Rows with the same id and text are
    one document in the counts, and each is returned; all rows of the least id keep a passage. Other columns are ignored. Rules and thresholds are the same at every size.
    """
    rows = docs.select("doc_id", "text", F.xxhash64("doc_id", "text").alias("key"))
    line = F.col("line")
    split = rows.where("text is not null").select("doc_id", "key", F.posexplode(F.split("text", "\n")).alias("at", "raw"))
    every = split.select("doc_id", "key", "at", masked(F.col("raw")).alias("line")).withColumn("leaf", leaf(line, depth))
    # A leaf of fewer lines than documents are needed can hold no template.
    leaves = scratch(every.groupBy("leaf").count().where(F.col("leaf").isNotNull() & (F.col("count") >= least_documents)).select("leaf", F.lit(True).alias("reached")), "leaves")
    every = every.withColumn("fixed", fixed_number(line))
    # A line that takes as many documents as a template does is left to the templates.
    passage = passages_needed(F.col("fixed"), least_documents, long_words) < least_documents
    wanted = every.join(leaves, "leaf", "left").where(F.col("reached") | passage)
    lines = scratch(
        wanted.select("doc_id", "key", "at", "leaf", "fixed", F.when(F.col("reached"), line).alias("line"), F.when(passage, F.xxhash64(F.lit(1), line)).alias("mark"), F.when(passage, F.xxhash64(F.lit(2), line)).alias("mark2")), "lines"
    )
    templated = lines.where("line is not null")
    distinct = scratch(templated.select("leaf", "line", "doc_id", "key").distinct().groupBy("leaf", "line").agg(F.count(F.lit(1)).alias("documents")), "distinct")
    named = scratch(line_templates(distinct, least_documents, depth, similarity, least_words).select("leaf", "line", F.xxhash64("leaf", "template").alias("template")), "named")
    placed = templated.join(named, ["leaf", "line"]).select("doc_id", "key", "at", "template")
    recurring = placed.select("template", "doc_id", "key").distinct().groupBy("template").agg(F.count(F.lit(1)).alias("documents")).where(F.col("documents") >= least_documents).select("template")
    passages = repeated_passages(lines.where("mark is not null").select("doc_id", "key", "at", "fixed", "mark", "mark2"), least_documents, long_words)
    dropped = placed.join(recurring, "template", "left_semi").select("doc_id", "key", "at").unionByName(passages)
    dropped = dropped.groupBy("doc_id", "key").agg(F.collect_set("at").alias("gone")).select(F.col("doc_id").alias("of"), F.col("key").alias("of_key"), "gone")
    both = rows.join(dropped, F.col("doc_id").eqNullSafe(F.col("of")) & (F.col("key") == F.col("of_key")), "left")
    cut = F.split("text", "\n", -1)
    kept = F.array_join(F.filter(cut, lambda x, i: ~F.coalesce(F.array_contains("gone", i), F.lit(False))), "\n")
    return both.select("doc_id", F.coalesce(F.when(F.col("text").isNotNull(), F.size(cut)), F.lit(0)).cast("long").alias("n_lines"), F.coalesce(F.size("gone"), F.lit(0)).cast("long").alias("n_dropped"), F.when(F.col("gone").isNull(), F.col("text")).otherwise(kept).alias("text"))
