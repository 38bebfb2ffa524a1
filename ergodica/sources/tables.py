"""The given tables (Parquet) and edge lists in other formats; sinks for chains and results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .work import written

CHAIN_SCHEMA = T.StructType([T.StructField("src", T.LongType(), False), T.StructField("dst", T.LongType(), False), T.StructField("prob", T.DoubleType(), False)])
RESULT_SCHEMA = T.StructType([T.StructField("state", T.LongType()), T.StructField("label", T.StringType()), T.StructField("pi", T.DoubleType())])
CONVERGENCE_SCHEMA = T.StructType(
    [T.StructField("chain", T.StringType()), T.StructField("method", T.StringType()), T.StructField("width", T.IntegerType()), T.StructField("depth", T.IntegerType())]
    + [T.StructField(c, T.LongType()) for c in ("iteration", "passes", "matvecs")]
    + [T.StructField(c, T.DoubleType()) for c in ("residual", "ritz_re", "ritz_im")]
    + [T.StructField("rank", T.IntegerType()), T.StructField("seconds", T.DoubleType())]
)

#: Columns a table must have to be what the builders take it for.
EXPECTED = {
    "events": {"event_id", "ts", "user_id", "event_type", "value", "props"},
    "lineitem": {"l_orderkey", "l_partkey", "l_suppkey"},
    "orders": {"o_orderkey", "o_custkey", "o_orderdate", "o_orderpriority"},
    "customer": {"c_custkey", "c_nationkey"},
    "supplier": {"s_suppkey", "s_nationkey"},
    "nation": {"n_nationkey", "n_regionkey", "n_name"},
    "embeddings": {"vec_id", "embedding"},
    "pages": {"page_id", "url", "html"},
    "documents": {"doc_id", "text"},
    "conversations": {"conv_id", "turn", "role"},
}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables; columns are pruned and filters pushed down by the scan."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if missing := EXPECTED.get(name, set()) - set(df.columns):
        raise ValueError(f"{name} lacks {sorted(missing)}")
    return df


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", cols: tuple[str, str, str] = ("src", "dst", "w"), kinds: tuple[str, str, str] = ("string", "string", "double"), **options) -> DataFrame:
    """An edge list as (src, dst, w). CSV and JSON rows that do not parse are dropped here; ``malformed`` returns them."""
    reader = spark.read.format(fmt).options(**options)
    if fmt in ("csv", "json"):
        reader = reader.schema(", ".join(f"`{c}` {k}" for c, k in zip(cols, kinds, strict=True)) + ", _corrupt_record string").option("mode", "PERMISSIVE")
    df = reader.load(path)
    if "_corrupt_record" in df.columns:
        df = df.where(F.col("_corrupt_record").isNull())
    return df.select(*(F.col(f"`{c}`").cast(k).alias(n) for c, k, n in zip(cols, kinds, ("src", "dst", "w"), strict=True))).where("src is not null and dst is not null and w is not null")


def malformed(spark: SparkSession, path: str, fmt: str, cols: tuple[str, str, str] = ("src", "dst", "w"), kinds: tuple[str, str, str] = ("string", "string", "double"), **options) -> DataFrame:
    schema = ", ".join(f"`{c}` {k}" for c, k in zip(cols, kinds, strict=True)) + ", _corrupt_record string"
    df = spark.read.format(fmt).options(**options).option("mode", "PERMISSIVE").schema(schema).load(path)
    parsed = written(df, "parsed")  # Spark refuses queries that need nothing but the corrupt record
    return parsed.where(F.col("_corrupt_record").isNotNull()).select("_corrupt_record", *cols)


def from_matrix(spark: SparkSession, rows: list[list[float]]) -> DataFrame:
    """A literal matrix as edges (src, dst, prob); zeros are dropped."""
    table = spark.createDataFrame([(i, [float(x) for x in r]) for i, r in enumerate(rows)], "src long, row array<double>")
    return table.select("src", F.posexplode("row").alias("dst", "prob")).where("prob <> 0").select("src", F.col("dst").cast("long").alias("dst"), "prob")


def write_chain(edges: DataFrame, path: str, blocks: int = 16) -> None:
    """Edges partitioned by ``src`` block, sorted by ``dst`` in each file: scans prune blocks, partial sums stay local."""
    placed = edges.withColumn("src_block", F.pmod(F.xxhash64("src"), F.lit(blocks)).cast("int"))
    placed.repartition("src_block").sortWithinPartitions("src_block", "dst").write.mode("overwrite").partitionBy("src_block").parquet(path)


def write_bucketed(edges: DataFrame, name: str, buckets: int = 16) -> None:
    """Edges as a catalog table bucketed on ``src``: the step's join never moves them again."""
    edges.write.mode("overwrite").bucketBy(buckets, "src").sortBy("dst").saveAsTable(name)


def read_chain(spark: SparkSession, path: str, src_blocks: list[int] | None = None) -> DataFrame:
    df = spark.read.parquet(path)
    return (df.where(F.col("src_block").isin(src_blocks)) if src_blocks is not None else df).select("src", "dst", "prob")


def write_result(df: DataFrame, path: str, mode: str = "append") -> None:
    df.write.mode(mode).parquet(path)
