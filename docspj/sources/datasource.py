"""A Python data source that loads a corpus of text files by name, and sinks."""

from __future__ import annotations

import os
from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType


class _Files(InputPartition):
    def __init__(self, names: list[str]):
        self.names = names


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.root, self.corpus, self.a_task = options["path"], options.get("corpus", "files"), int(options.get("filesPerTask", "64"))

    def partitions(self) -> list[InputPartition]:
        names = sorted(os.path.join(d, n) for d, _, ns in os.walk(self.root) for n in ns if n.endswith((".txt", ".md", ".html")))
        return [_Files(names[i : i + self.a_task]) for i in range(0, len(names), self.a_task)] or [_Files([])]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        for name in partition.names:
            with open(name, encoding="utf-8", errors="replace") as f:
                yield (self.corpus, os.path.relpath(name, self.root), f.read())


class CorpusSource(DataSource):
    """spark.read.format("docspj_corpus").option("corpus", name).load(folder): a document a text file.

    For folders that all executors mount; files in stores come through Spark's own readers (wholetext).
    """

    @classmethod
    def name(cls) -> str:
        return "docspj_corpus"

    def schema(self) -> str:
        return "corpus string, doc_key string, text string"

    def reader(self, schema: StructType) -> DataSourceReader:
        return _Reader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(CorpusSource)


def write_partitioned(df: DataFrame, path: str, by: str, kind: str = "parquet") -> None:
    """A cache or ledger by attribute: a folder a value, dealt by it first so that each folder has few files."""
    df.repartition(by).write.mode("append").partitionBy(by).format(kind).save(path)


def write_bucketed(df: DataFrame, table: str, key: str = "doc_key", buckets: int = 8) -> None:
    """A table whose joins and aggregations by key need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def each_batch(path: str, key: str = "batch") -> Callable[[DataFrame, int], None]:
    """A foreachBatch writer that a repeated batch does not duplicate: each batch is its own folder, overwritten."""

    def write(df: DataFrame, batch: int) -> None:
        df.write.mode("overwrite").parquet(f"{path}/{key}={batch}")

    return write
