"""Sources and sinks: the given tables, round trips through file formats, partitioned and bucketed output."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

from waysite.session import ship_code

#: Spark's own switch for dropping a query's shuffle files at its end.
SHUFFLE_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def read_table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A given table; only the named columns reach the scan."""
    ship_code(spark)
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share (spark.checkpoint.dir). Where it is unset a local session gets a folder
    of its own; a cluster would not see that one, so there it is an error."""
    sc = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None) or sc.getConf().get("spark.checkpoint.dir", None)
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        if not named and not sc.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="waysite-"))
    return (named or sc._jsc.sc().getCheckpointDir().get()).rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


@contextmanager
def dropping_shuffles(spark: SparkSession) -> Iterator[None]:
    """Shuffle files of the jobs inside go as soon as their job ends, not when the driver next collects garbage."""
    before = spark.conf.get(SHUFFLE_CLEANUP)
    spark.conf.set(SHUFFLE_CLEANUP, "true")
    try:
        yield
    finally:
        spark.conf.set(SHUFFLE_CLEANUP, before)


def materialize(df: DataFrame, name: str = "relation", compression: str = "snappy") -> DataFrame:
    """Write once, read back: a short lineage that survives lost executors. Nothing of the job that wrote it is needed
    again, so its shuffle files go at once."""
    path = fresh_path(df.sparkSession, name)
    with dropping_shuffles(df.sparkSession):
        df.write.option("compression", compression).parquet(path)
    back = df.sparkSession.read.schema(df.schema).parquet(path)
    back.written_at = path
    return back


def discard(*tables: DataFrame) -> None:
    """Delete materialized tables that nothing reads any more."""
    for df in tables:
        path = df.sparkSession._jvm.org.apache.hadoop.fs.Path(df.written_at)
        path.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def round_trip(df: DataFrame, fmt: str, **options) -> DataFrame:
    """df through a file format (csv, json, orc, parquet, text) with its schema declared on reading."""
    path = fresh_path(df.sparkSession, fmt)
    df.write.format(fmt).options(**options).save(path)
    return df.sparkSession.read.format(fmt).options(**options).schema(df.schema).load(path)


def write_partitioned(df: DataFrame, path: str, *columns: str) -> None:
    df.write.mode("overwrite").partitionBy(*columns).parquet(path)


def write_bucketed(df: DataFrame, table: str, buckets: int, *columns: str) -> DataFrame:
    """A table bucketed and sorted by columns, so that later joins on them need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, *columns).sortBy(*columns).format("parquet").saveAsTable(table)
    return df.sparkSession.table(table)


def jdbc_options(url: str, table: str, column: str, low: int, high: int, parts: int) -> dict[str, str]:
    """Options for spark.read.format('jdbc'): a partitioned read of a relation kept in a database."""
    return {"url": url, "dbtable": table, "partitionColumn": column, "lowerBound": str(low), "upperBound": str(high), "numPartitions": str(parts)}
