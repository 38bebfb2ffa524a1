"""What the operators share: reading tables, tables written to the shared folder, one batch interface to Arrow."""

from __future__ import annotations

import ctypes
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space that separates words: 0x20 and 0x09 to 0x0D, the set of ``bytes.split()``.
SPACE_CLASS = r"\x20\x09-\x0D"
WORD = rf"[^{SPACE_CLASS}]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: the session's ``spark.checkpoint.dir``; a temporary one only where it is unset and driver and executors are one process."""
    where = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not where:
        if not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        spark.sparkContext.setCheckpointDir(f"file://{tempfile.mkdtemp(prefix='ergodica-')}")
        where = spark.sparkContext.getCheckpointDir()
    return where.rstrip("/")


def work_path(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder; Hadoop removes it when the driver's JVM ends."""
    path = f"{shared_dir(spark)}/ergodica/{name}-{uuid.uuid4().hex}"
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(hadoop)
    return path


def written(df: DataFrame, name: str, codec: str | None = None) -> DataFrame:
    """Cut the lineage: write ``df`` as Parquet into the shared folder and read it again, so that lost executors cost nothing before it."""
    path = work_path(df.sparkSession, name)
    df.write.parquet(path, compression=codec)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def give_back() -> None:
    """Return a Python worker's freed memory to the system: it lives on for other tasks and stages."""
    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
        trim(0)


def slices(batch: pa.RecordBatch, most: int) -> Iterator[pa.RecordBatch]:
    """Runs of a batch's rows of some ``most`` bytes each, one row at least."""
    if batch.num_rows:
        step = max(1, batch.num_rows * most // max(1, batch.nbytes))
        yield from (batch.slice(at, step) for at in range(0, batch.num_rows, step))


def in_batches(df: DataFrame, kernel: Callable[[pa.Table], Iterator[pa.RecordBatch] | Iterator[pa.Table]], schema: str, most: int = 4 << 20) -> DataFrame:
    """``mapInArrow`` whose kernel sees tables of some ``most`` bytes: bounded memory, however large the partition is."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, most):
                for out in kernel(pa.Table.from_batches([part])):
                    yield from out.to_batches() if isinstance(out, pa.Table) else (out,)
        give_back()

    return df.mapInArrow(run, schema)


def slim(docs: DataFrame, *names: str) -> DataFrame:
    """Only the named columns, under their own names, whatever else the table carries."""
    return docs.select(*(F.col(f"`{n}`") for n in names))


def joined_by_key(rows: DataFrame, facts: DataFrame, key: str, count: str = "n") -> DataFrame:
    """``rows`` joined with ``facts``, a written table of one row for each key with its number of rows in ``count`` (dropped), without a hot task.

    Keys with more rows than an even share of a partition are fewer than the partitions: their facts are broadcast and their rows stay where
    they lie; the rest is joined by shuffle.
    """
    total = facts.agg(F.sum(count)).first()[0] or 0
    share = max(1, total // int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    hot, rest = F.broadcast(facts.where(F.col(count) > share).drop(count)), facts.where(F.col(count) <= share).drop(count)
    return rows.join(hot, key).unionByName(rows.join(hot.select(key), key, "left_anti").join(rest, key))
