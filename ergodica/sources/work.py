"""Tables written to the shared folder to cut lineage inside iterations."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The session's ``spark.checkpoint.dir``; a temporary one only where it is unset and driver and executors are one process."""
    where = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not where:
        if not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        spark.sparkContext.setCheckpointDir(f"file://{tempfile.mkdtemp(prefix='ergodica-')}")
        where = spark.sparkContext.getCheckpointDir()
    return where.rstrip("/")


def _new_path(spark: SparkSession, name: str) -> str:
    path = f"{shared_dir(spark)}/ergodica/{name}-{uuid.uuid4().hex}"
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(at)
    return path


def written(df: DataFrame, name: str = "step") -> DataFrame:
    """``df`` as a Parquet table in the shared folder, read again; removed by ``discard``, or when the driver's JVM ends."""
    spark = df.sparkSession
    path = _new_path(spark, name)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._ergodica_place = (path, None)
    return out


def bucketed(df: DataFrame, keys: list[str], buckets: int, name: str = "bucketed") -> DataFrame:
    """The same as a table dealt by ``keys`` into ``buckets`` files: joins and sums on the keys with as many partitions never move it again."""
    spark = df.sparkSession
    path = _new_path(spark, name)
    table = f"ergodica_{name}_{path[-32:]}"
    df.repartition(buckets, *keys).write.option("path", path).bucketBy(buckets, *keys).sortBy(*keys).saveAsTable(table)
    out = spark.table(table)
    out._ergodica_place = (path, table)
    return out


def discard(*frames: DataFrame) -> None:
    """Remove the files of tables from ``written`` or ``bucketed`` that nothing reads any more; other frames are left alone."""
    for df in frames:
        if place := getattr(df, "_ergodica_place", None):
            path, table = place
            spark = df.sparkSession
            if table:
                spark.sql(f"DROP TABLE IF EXISTS {table}")
            at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)
