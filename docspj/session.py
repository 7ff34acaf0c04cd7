"""Sessions, and durable cuts of a plan."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

#: What a session of one's own is started with. A session as given is used as it is.
SETTINGS = {
    "spark.sql.adaptive.enabled": "true",
    "spark.sql.adaptive.skewJoin.enabled": "true",
    "spark.sql.optimizer.runtime.bloomFilter.enabled": "true",
    "spark.sql.session.timeZone": "UTC",
    "spark.speculation": "false",
    "spark.scheduler.mode": "FAIR",
}


def session(master: str = "local[*]", **settings: str) -> SparkSession:
    """A session for this engine. Speculation is off: a second attempt of a reading task costs tokens."""
    builder = SparkSession.builder.master(master)
    for k, v in (SETTINGS | settings).items():
        builder = builder.config(k, v)
    return builder.getOrCreate()


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: what the cluster names. Where none is named, one of this machine, if the master is local too."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not named:
        given = spark.sparkContext._jsc.sc().getCheckpointDir()
        named = given.get() if given.isDefined() else None
    if not named:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        named = "file://" + tempfile.mkdtemp(prefix="docspj-")
        spark.sparkContext.setCheckpointDir(named)
    return named.rstrip("/") if ":" in named else "file://" + named.rstrip("/")


def cut(df: DataFrame, label: str = "cut") -> DataFrame:
    """df written to the shared folder and read back: nothing before it, least of all a paid extraction, is computed twice."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/docspj/{label}-{uuid.uuid4().hex}"
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(hadoop)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)
