"""What the corpus operators share: reading tables, durable cuts of a plan, word counts."""

from __future__ import annotations

import uuid
from collections.abc import Iterable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from docspj.session import shared_dir

#: White space of the contracts: blank, tab, line feed, vertical tab, form feed, carriage return.
SPACE_CHARS = " \t\n\x0b\x0c\r"
WORD_PATTERN = r"[^\x20\x09-\x0D]+"
DOCUMENT_COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


#: A worker holds what it works on several times over: pieces of so many rows, and bytes, at most. One row alone may be longer.
PIECE_ROWS, PIECE_BYTES = 2000, 16 << 20
_ROWS_SETTING = "spark.sql.execution.arrow.maxRecordsPerBatch"


def release() -> None:
    """Give freed memory back to the system: workers serve one task after another, and what one freed would count beside what the next takes."""
    import ctypes
    import gc

    import pyarrow as pa

    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library: nothing to trim
        return


def slices(batches):
    """Arrow batches cut into parts of bounded rows and bytes; Spark itself bounds a batch by spark.sql.execution.arrow.maxBytesPerBatch."""
    release()
    for batch in batches:
        rows = max(1, min(PIECE_ROWS, batch.num_rows * PIECE_BYTES // max(1, batch.nbytes)))
        for low in range(0, batch.num_rows, rows):
            yield batch.slice(low, rows)
        batch = None
    release()


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table, and, as texts are long, no more than PIECE_ROWS rows a batch between the JVM and Python in this session from here on: only a
    session's setting bounds what the JVM buffers of a batch."""
    if int(spark.conf.get(_ROWS_SETTING, "10000")) > PIECE_ROWS:
        spark.conf.set(_ROWS_SETTING, str(PIECE_ROWS))
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def scratch_path(spark: SparkSession, label: str) -> str:
    """A new path in the shared folder, deleted when the driver's JVM ends."""
    path = f"{shared_dir(spark)}/docspj/{label}-{uuid.uuid4().hex}"
    jvm = spark.sparkContext._jvm
    hadoop_path = jvm.org.apache.hadoop.fs.Path(path)
    hadoop_path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(hadoop_path)
    return path


def scratch(df: DataFrame, label: str) -> DataFrame:
    """Write df as Parquet to the shared folder and read it back: a cut of the lineage that outlives executors."""
    spark = df.sparkSession
    path = scratch_path(spark, label)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def word_count(text: Column) -> Column:
    """Words of a text; null has none."""
    return F.when(text.isNull(), F.lit(0)).otherwise(F.regexp_count(text, F.lit(WORD_PATTERN))).cast("long")


def held_out(doc_id: Column, modulus: int = 4, rest: int = 2) -> Column:
    """Rows that no model may learn from: crc32 of the id as text leaves `rest`; a null id counts as held out."""
    return F.coalesce(F.crc32(doc_id.cast("string")) % modulus == rest, F.lit(True))


def only(df: DataFrame, columns: Iterable[str]) -> DataFrame:
    """The named columns alone, so that extra columns of any name can't clash with those an operator adds."""
    return df.select(*[F.col(f"`{c}`") for c in columns])


def bounded_sample(df: DataFrame, key: str, rows: int, seed: int) -> DataFrame:
    """The `rows` rows of least seeded hash of key: the same on every run and every partitioning."""
    return df.orderBy(F.xxhash64(F.lit(seed), F.col(key).cast("string")), F.col(key)).limit(rows)


def keep_rows(df: DataFrame, text_column: str, decide) -> DataFrame:
    """The rows of df, all their columns unchanged, for which decide(list of texts) -> list of booleans says so."""
    import pyarrow as pa

    at = df.columns.index(text_column)

    def of(batches):
        for batch in slices(batches):
            if batch.num_rows:
                yield batch.filter(pa.array(decide(batch.column(at).to_pylist()), pa.bool_()))

    return df.mapInArrow(of, df.schema)
