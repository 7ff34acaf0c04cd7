"""Readers of values: rules, rules with noise, callables for models; and the cache of what was read."""

from __future__ import annotations

import re
import time
from collections.abc import Callable, Iterable, Iterator
from concurrent.futures import ThreadPoolExecutor, TimeoutError as Late

import pandas as pd
from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from docspj.functions.text import md5_rank, n_tokens
from docspj.model import Attribute
from docspj.operators.retrieval import extract


def noisy(seed: str = "noise", base: float = 0.98, slope: float = 0.00004) -> Callable[[Column, Attribute], Column]:
    """A rule extractor that is right with a chance that falls with every token it is given: long contexts mislead readers."""

    def read(text: Column, a: Attribute) -> Column:
        right = md5_rank(F.concat(F.lit(a.name), F.substring(text, 1, 400)), seed) < F.greatest(F.lit(0.0), F.lit(base) - slope * n_tokens(text))
        return F.when(right, extract(text, a))

    return read


def read_batch(rows: DataFrame, reader: Callable[[str, str], str | None], threads: int = 8, retries: int = 2, seconds: float = 60.0) -> DataFrame:
    """rows(key, attr, text) -> (key, attr, value, tokens_in, tokens_out, failed): one call a row, several at a time in each task.

    A call that fails or is late is tried again; then it counts as failed and its value is null. Speculative execution should be off.
    """
    key = rows.columns[0]

    def of(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        with ThreadPoolExecutor(threads) as pool:

            def ask(attr: str, text: str) -> tuple[str | None, bool]:
                for attempt in range(retries + 1):
                    try:
                        return reader(attr, text), False
                    except Exception:  # noqa: BLE001  whatever the caller's reader raises
                        time.sleep(min(5.0, 0.05 * 2**attempt))
                return None, True

            for frame in batches:
                calls = [pool.submit(ask, a, t) for a, t in zip(frame["attr"], frame["text"], strict=True)]
                found = []
                for c in calls:
                    try:
                        found.append(c.result(timeout=seconds))
                    except Late:
                        found.append((None, True))
                values = [None if v is None else str(v) for v, _ in found]
                yield pd.DataFrame({key: frame[key], "attr": frame["attr"], "value": values, "tokens_in": [len(t.split()) for t in frame["text"]], "tokens_out": [len(v.split()) if v else 0 for v in values], "failed": [f for _, f in found]})

    kind = rows.schema[key].dataType.simpleString()
    return rows.select(key, "attr", "text").mapInPandas(of, f"{key} {kind}, attr string, value string, tokens_in long, tokens_out long, failed boolean")


class ExtractionCache:
    """Values read before, as Parquet by attribute; the same folder serves queries that run at once."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path

    def rows(self) -> DataFrame:
        try:
            found = self.spark.read.parquet(self.path)
        except AnalysisException:
            found = self.spark.createDataFrame([], "doc_key string, value string, tokens_in long, tokens_out long, attr string")
        return found.select("doc_key", "attr", "value", "tokens_in", "tokens_out").dropDuplicates(["doc_key", "attr"])

    def misses(self, asked: DataFrame) -> DataFrame:
        """asked(doc_key, attr, text) without what is held."""
        return asked.join(self.rows().select("doc_key", "attr"), ["doc_key", "attr"], "left_anti")

    def put(self, rows: DataFrame) -> None:
        """Keep rows(doc_key, attr, value, tokens_in, tokens_out) that were read."""
        rows.select("doc_key", "value", "tokens_in", "tokens_out", "attr").write.mode("append").partitionBy("attr").parquet(self.path)

    def read(self, asked: DataFrame, reader: Callable[[DataFrame], DataFrame]) -> tuple[DataFrame, int]:
        """Values for all of asked, and the tokens that those not held cost. They are in the cache before anyone uses them."""
        new = reader(self.misses(asked)).select("doc_key", "attr", "value", "tokens_in", "tokens_out")
        before = self.rows().agg(F.coalesce(F.sum(F.col("tokens_in") + F.col("tokens_out")), F.lit(0))).first()[0]
        self.put(new)
        held = self.rows()
        after = held.agg(F.coalesce(F.sum(F.col("tokens_in") + F.col("tokens_out")), F.lit(0))).first()[0]
        return asked.select("doc_key", "attr").join(held, ["doc_key", "attr"], "left"), int(after - before)


def cost_with_cache(costs: DataFrame, cache: ExtractionCache) -> DataFrame:
    """costs(doc_key, attr, tokens): what is held costs nothing."""
    held = cache.rows().select("doc_key", "attr", F.lit(True).alias("held"))
    return costs.join(held, ["doc_key", "attr"], "left").select("doc_key", "attr", F.when(F.col("held"), 0).otherwise(F.col("tokens")).cast("bigint").alias("tokens"))


def approx_from_sample(values: DataFrame, column: str, total: int) -> DataFrame:
    """Sum and mean of a column estimated from sampled tuples, with 95 % intervals. An extension."""
    s = values.agg(F.count(column).alias("n"), F.avg(column).alias("mean"), F.coalesce(F.stddev_samp(column), F.lit(0.0)).alias("sd"))
    half = 1.96 * F.col("sd") / F.sqrt(F.greatest(F.col("n"), F.lit(1)))
    return s.select("n", "mean", half.alias("half_width"), (F.col("mean") * total).alias("sum"), (half * total).alias("sum_half_width"))


def rule_reader(attributes: Iterable[Attribute], on_call: Callable[[str, str], None] | None = None) -> Callable[[str, str], str | None]:
    """A reader that stands for a model: the attributes' own patterns, one call an attribute and text, or several attributes of a text in one call.

    Names joined by commas are answered by values joined by line feeds. on_call sees every call.
    """
    by_name = {a.name: a for a in attributes}

    def one(a: Attribute, text: str) -> str | None:
        if a.pattern.startswith("count:"):
            return str(len(re.findall(a.pattern[6:], text)))
        if a.pattern.startswith("has:"):
            return str(re.search(a.pattern[4:], text) is not None).lower()
        m = re.search(a.pattern, text)
        return m.group(1) or None if m else None

    def read(names: str, text: str) -> str | None:
        if on_call is not None:
            on_call(names, text)
        if "," not in names:
            return one(by_name[names], text)
        return "\n".join(one(by_name[n], text) or "" for n in names.split(","))

    return read
