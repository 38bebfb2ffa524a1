"""How edges lie between passes: dealt by source once, hubs over several buckets, kept."""

from __future__ import annotations

from dataclasses import replace

from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.chain import Chain
from ..sources.work import bucketed, written

SALTS = 16


def laid_out(chain: Chain, buckets: int | None = None, least_hub: int = 10_000) -> Chain:
    """Edges as a table bucketed by source, as many buckets as shuffle partitions: passes move blocks and partial sums, never edges.

    A source with more than a bucket's even share of the edges (and ``least_hub`` of them) is a hub: its edges are dealt by destination over
    ``SALTS`` buckets. There are fewer hubs than buckets, so their table is small whatever the chain's size.
    """
    n = buckets or int(chain.edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    exits = chain.edges.groupBy("src").agg(F.count("*").alias("exits"))
    most = max(least_hub, (exits.agg(F.sum("exits")).first()[0] or 0) // n)
    hubs = written(exits.where(F.col("exits") > most).select("src", F.lit(SALTS).alias("salts")), "hubs")
    edges = chain.edges.select("src", "dst", "prob")
    if hubs.isEmpty():
        return replace(chain, edges=bucketed(edges, ["src"], n, "edges"))
    return replace(chain, edges=bucketed(salted_edges(edges, hubs), ["src", "salt"], n, "edges"), hubs=hubs)


def salted_edges(edges: DataFrame, hubs: DataFrame) -> DataFrame:
    """Edges with ``salt``: 0, or for sources in ``hubs`` (src, salts) a hash of the destination."""
    marked = edges.join(F.broadcast(hubs), "src", "left")
    return marked.withColumn("salt", F.when(F.col("salts").isNull(), 0).otherwise(F.pmod(F.xxhash64("dst"), F.col("salts"))).cast("int")).drop("salts")


def prepare(chain: Chain, partitions: int | None = None, storage: str = "cached") -> Chain:
    """cached: edges dealt by ``src`` and persisted (memory, then disk; rebuilt if an executor is lost); scan: as they are, read at each pass."""
    if storage == "scan":
        return chain
    n = partitions or int(chain.edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = chain.edges.repartition(n, "src").sortWithinPartitions("dst")
    return replace(chain, edges=dealt.persist(StorageLevel.MEMORY_AND_DISK))


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
