"""Reading tables and writing relations for reuse."""

from __future__ import annotations

import gc
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register(spark: SparkSession, sf_dir: str, names: list[str]) -> None:
    for n in names:
        table(spark, sf_dir, n).createOrReplaceTempView(n)


def write_bucketed(df: DataFrame, name: str, keys: list[str], buckets: int) -> DataFrame:
    """A relation bucketed and sorted by its join key: joins on that key need no shuffle of it."""
    df.write.mode("overwrite").bucketBy(buckets, *keys).sortBy(*keys).format("parquet").saveAsTable(name)
    return df.sparkSession.table(name)


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share, from spark.checkpoint.dir; on one machine a folder of our own where that is unset."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        found = "file:/tmp/mmquery-shared"
    return found.rstrip("/")


#: Paths of the tables cut in each open dropped_after(), innermost last.
_DROPPED: list[list[str]] = []


@contextmanager
def dropped_after(spark: SparkSession) -> Iterator[None]:
    """Tables cut inside are deleted at the end, and the JVM is asked to let go of what was shuffled for them."""
    _DROPPED.append([])
    try:
        yield
    finally:
        jvm = spark.sparkContext._jvm
        for f in _DROPPED.pop():
            p = jvm.org.apache.hadoop.fs.Path(f)
            p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
        let_go(spark)


def let_go(spark: SparkSession) -> None:
    """Shuffle files of frames that nothing holds any more are deleted once both sides have collected their garbage."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def cut(df: DataFrame, name: str = "step") -> DataFrame:
    """Cut lineage by a table in the shared folder: read again, not made again, where an executor is lost or a plan uses it twice."""
    path = f"{shared_dir(df.sparkSession)}/mmquery/{name}-{uuid.uuid4().hex}"
    if _DROPPED:
        _DROPPED[-1].append(path)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def bounded_broadcast(df: DataFrame, most_rows: int) -> DataFrame:
    """A broadcast hint only where a count shows the rows to be few; otherwise Spark chooses."""
    return F.broadcast(df) if df.limit(most_rows + 1).count() <= most_rows else df
