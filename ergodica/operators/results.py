"""What users do with a stationary vector: top states, running mass, set operations, tables of sweeps."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..sources.work import written


def top_states(pi: DataFrame, k: int) -> DataFrame:
    return pi.orderBy(F.desc("pi"), "state").limit(k)


def top_per_group(pi: DataFrame, group: str, k: int) -> DataFrame:
    w = Window.partitionBy(group).orderBy(F.desc("pi"), "state")
    return pi.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def prefix_sums(df: DataFrame, value: str, *order) -> DataFrame:
    """df with ``running``: the sum of ``value`` down to each row in ``order``, without a single-partition window.

    Rows are range-partitioned and written; each partition sums its own, and the sums of the partitions before it (one number each) are added.
    """
    placed = written(df.repartitionByRange(*order).withColumn("__part", F.spark_partition_id()), "prefix")
    sums = placed.groupBy("__part").agg(F.sum(value).alias("__s"))
    before = sums.select("__part", F.sum("__s").over(Window.orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)).alias("__base"))  # a row for each partition
    w = Window.partitionBy("__part").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    return placed.join(F.broadcast(before), "__part").withColumn("running", F.sum(value).over(w) + F.coalesce("__base", F.lit(0.0))).drop("__part", "__base")


def running_mass(pi: DataFrame) -> DataFrame:
    """state, pi, running: mass down to each state by falling pi."""
    return prefix_sums(pi.select("state", "pi"), "pi", F.desc("pi"), F.col("state"))


def last_checks(log: DataFrame) -> DataFrame:
    """The last row of each run."""
    w = Window.partitionBy("chain", "method", "width", "depth").orderBy(F.desc("iteration"))
    return log.withColumn("r", F.row_number().over(w)).where("r = 1").drop("r")


def pivot_grid(log: DataFrame, value: str = "matvecs") -> DataFrame:
    """Widths down, depths across."""
    last = last_checks(log)
    return last.groupBy("chain", "width").pivot("depth").agg(F.first(value))


def savings(log: DataFrame) -> DataFrame:
    """chain, method, width, depth, iteration, matvecs, saving: per cent fewer matvecs than the power method of the chain."""
    last = last_checks(log)
    base = last.where("width = 1 and depth = 1").groupBy("chain").agg(F.max("matvecs").alias("base"))
    return last.join(base, "chain").select("chain", "method", "width", "depth", "iteration", "matvecs", (100 * (1 - F.col("matvecs") / F.col("base"))).alias("saving"))


def savings_cube(log: DataFrame) -> DataFrame:
    return savings(log).cube("chain", "width", "depth").agg(F.max("saving").alias("best"), F.grouping_id().alias("level"))


def state_setop(a: DataFrame, b: DataFrame, op: str, all: bool = False) -> DataFrame:
    """union, intersect or except of two state sets."""
    a, b = a.select("state"), b.select("state")
    if op == "union":
        return a.union(b) if all else a.union(b).distinct()
    if op == "intersect":
        return a.intersectAll(b) if all else a.intersect(b)
    if op == "except":
        return a.exceptAll(b) if all else a.subtract(b)
    raise ValueError(op)
