"""SQL-callable functions: table functions over texts, an embedder around a model, a centroid aggregate."""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import ArrayType, DoubleType, FloatType, IntegerType, StringType, StructField, StructType

_CUT = re.compile(r"(?<=[.!?])\s+|\n+")


@udtf(returnType=StructType([StructField("pos", IntegerType()), StructField("sentence", StringType())]))
class Sentences:
    """Sentences of a text."""

    def eval(self, text: str) -> Iterator[tuple[int, str]]:
        for i, s in enumerate(x.strip() for x in _CUT.split(text or "") if x.strip()):
            yield i, s


@udtf(returnType=StructType([StructField("seg_no", IntegerType()), StructField("segment", StringType())]))
class Segments:
    """Runs of sentences of at most so many tokens."""

    def eval(self, text: str, tokens: int) -> Iterator[tuple[int, str]]:
        held, n, number = [], 0, 0
        for s in (x.strip() for x in _CUT.split(text or "") if x.strip()):
            if held and n + len(s.split()) > tokens:
                yield number, " ".join(held)
                held, n, number = [], 0, number + 1
            held.append(s)
            n += len(s.split())
        if held:
            yield number, " ".join(held)


def callable_embedder(model: Callable[[list[str]], list[list[float]]]) -> Callable[[Column], Column]:
    """A Column function around a model that embeds lists of texts; texts come in Arrow batches."""

    @pandas_udf(ArrayType(FloatType()))
    def embed(texts: pd.Series) -> pd.Series:
        return pd.Series([list(map(float, v)) for v in model(texts.fillna("").tolist())])

    return embed


@pandas_udf(ArrayType(DoubleType()))
def centroid(vectors: pd.Series) -> list:
    """Mean of the vectors of a group."""
    rows = [v for v in vectors if v is not None]
    return [float(sum(c) / len(rows)) for c in zip(*rows, strict=True)] if rows else []


def register(spark: SparkSession) -> None:
    spark.udtf.register("sentences_of", Sentences)
    spark.udtf.register("segments_of", Segments)
    spark.udf.register("centroid", centroid)
