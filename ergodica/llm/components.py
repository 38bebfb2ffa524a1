"""Connected components of a link table by alternating star contractions: union-find for links that no machine holds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written


def _oriented(links: DataFrame) -> DataFrame:
    """Distinct links from the larger to the smaller end, without loops and nulls."""
    return links.where(F.col("a") != F.col("b")).select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()


def _large_star(links: DataFrame) -> DataFrame:
    both = links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
    return _oriented(both.join(least, "a").where(F.col("b") > F.col("a")).select(F.col("b").alias("a"), F.col("m").alias("b")))


def _small_star(links: DataFrame) -> DataFrame:
    least = links.groupBy("a").agg(F.min("b").alias("m"))
    return _oriented(links.join(least, "a").select(F.explode(F.array("a", "b")).alias("a"), F.col("m").alias("b")))


def _mark(links: DataFrame) -> tuple:
    return tuple(links.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())


def components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """links (a, b of one ordered type) to ``node, component`` for every linked node; component is the least node reachable.

    Each round is two aggregations and joins on hashed keys; hubs are split by the adaptive skew join. The rounds grow
    with the logarithm of the longest path. No links: an empty table. Raises if ``most_rounds`` do not settle it.
    """
    now = written(_oriented(links), "links")
    mark = _mark(now)
    for _ in range(most_rounds if mark[0] else 0):
        now = written(_small_star(_large_star(now)), "links")
        if (new := _mark(now)) == mark:
            break
        mark = new
    else:
        if mark[0]:
            raise RuntimeError("the components did not settle")
    roots = now.select(F.col("b").alias("node")).distinct()
    return now.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(roots.select("node", F.col("node").alias("component")))
