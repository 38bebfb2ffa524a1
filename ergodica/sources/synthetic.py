"""Generated chains: the five-state example, a release site of N four-state channels, ladders, cycles and blocks."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from math import comb

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .tables import from_matrix

# The transition probabilities of the five-state example.
FIVE_STATE = [
    [0.0, 0.0, 0.0, 0.9090, 0.0910],
    [0.0002, 0.0, 0.9998, 0.0, 0.0],
    [0.0, 0.9998, 0.0, 0.0002, 0.0],
    [0.6690, 0.0, 0.0, 0.0, 0.3310],
    [0.9989, 0.0011, 0.0, 0.0, 0.0],
]


def five_state(spark: SparkSession) -> DataFrame:
    return from_matrix(spark, FIVE_STATE)


def birth_death(spark: SparkSession, states: int, up: float = 0.3, down: float = 0.2) -> DataFrame:
    """A ladder; its stationary vector has product form, (up/down)^state."""
    s = spark.range(states).withColumnRenamed("id", "src")
    u, d = F.when(F.col("src") < states - 1, F.lit(up)).otherwise(0.0), F.when(F.col("src") > 0, F.lit(down)).otherwise(0.0)
    moves = F.array(F.struct((F.col("src") + 1).alias("dst"), u.alias("prob")), F.struct((F.col("src") - 1).alias("dst"), d.alias("prob")), F.struct(F.col("src").alias("dst"), (1 - u - d).alias("prob")))
    return s.select("src", F.inline(moves)).where("prob > 0")


def cycle(spark: SparkSession, states: int) -> DataFrame:
    return spark.range(states).select(F.col("id").alias("src"), ((F.col("id") + 1) % states).alias("dst"), F.lit(1.0).alias("prob"))


def block_coupled(spark: SparkSession, groups: int, size: int, eps: float) -> DataFrame:
    """``groups`` complete groups, weakly joined in a ring: ``groups`` eigenvalues near 1. Symmetric weights."""
    s = spark.range(groups * size).select(F.col("id").alias("src"), F.expr(f"id div {size}").alias("g"))
    inner = s.select("src", F.explode(F.sequence(F.col("g") * size, F.col("g") * size + size - 1)).alias("dst"), F.lit(1.0).alias("w"))
    ring = s.where(F.col("src") % size == 0).select(F.col("src"), ((F.col("src") + size) % (groups * size)).alias("dst"), F.lit(float(eps)).alias("w"))
    both = inner.where("src <> dst").unionByName(ring).unionByName(ring.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))
    w = both.groupBy("src", "dst").agg(F.sum("w").alias("w"))
    return w.join(w.groupBy("src").agg(F.sum("w").alias("t")), "src").select("src", "dst", (F.col("w") / F.col("t")).alias("prob"))


@dataclass(frozen=True)
class Rates:
    """Own rates of the release site (x = ions / capacity); invented, not published ones.

    Opening: open_base + feedback x^2. Ions come at (influx + release * open channels) * capacity + influx_flat and go at loss * ions, and
    loss_flat while there are any. The defaults pull the ions to a mean, so many modes are about equally slow.
    """

    open_base: float = 0.04
    feedback: float = 1.0
    close: float = 1.0
    inactivate: float = 0.02
    inactivate_flat: float = 0.0
    recover: float = 0.02
    influx: float = 0.02
    release: float = 0.2
    loss: float = 0.1
    influx_flat: float = 0.0
    loss_flat: float = 0.0


#: Ions wander freely: a few slow modes, then the channels' own, faster ones. Their number is equally often any.
WANDERING = Rates(open_base=0.4, feedback=0.3, close=0.6, inactivate=0.0, inactivate_flat=0.2, recover=0.2, influx=0.0, release=0.0, loss=0.0, influx_flat=1.0, loss_flat=1.0)
#: Ions are pumped out ten times as fast as they come: their number is geometric with ratio 0.1, whatever the capacity.
PUMPED = Rates(open_base=0.1, feedback=0.1, close=0.1, inactivate=0.0, inactivate_flat=0.05, recover=0.05, influx=0.0, release=0.0, loss=0.0, influx_flat=0.1, loss_flat=1.0)


def release_site_size(channels: int, capacity: int) -> int:
    return comb(channels + 3, 3) * (capacity + 1)


def state_id(o: Column, i: Column, ci: Column, ions: Column, channels: int, capacity: int) -> Column:
    b = channels + 1
    return (((o * b + i) * b + ci) * (capacity + 1) + ions).cast("long")


def release_site_states(spark: SparkSession, channels: int, capacity: int) -> DataFrame:
    """state, closed, open, inact, cinact, ions: every configuration of the channels (counted) times every ion number; no shuffle."""
    b = channels + 1
    d = spark.range(b**3).select(F.expr(f"id div {b * b}").alias("open"), F.expr(f"(id div {b}) % {b}").alias("inact"), (F.col("id") % b).alias("cinact")).where(F.col("open") + F.col("inact") + F.col("cinact") <= channels)
    d = d.select("*", (channels - F.col("open") - F.col("inact") - F.col("cinact")).alias("closed"), F.explode(F.expr(f"sequence(0L, {capacity}L)")).alias("ions"))
    return d.select(state_id(F.col("open"), F.col("inact"), F.col("cinact"), F.col("ions"), channels, capacity).alias("state"), "closed", "open", "inact", "cinact", "ions")


def moves_of(c, o, i, ci, ions, capacity: int, rates: Rates, where: Callable) -> list[tuple[tuple[int, int, int, int], object]]:
    """(change of open, inact, cinact, ions; rate) of each kind of move from a state; numbers and columns alike, with ``where(condition, value)`` for 0 elsewhere."""
    x = ions / capacity
    opening = rates.open_base + rates.feedback * x * x
    inactivation = rates.inactivate * (rates.open_base + x) + rates.inactivate_flat
    return [
        ((1, 0, 0, 0), c * opening), ((-1, 0, 0, 0), o * rates.close), ((0, 1, -1, 0), ci * opening), ((0, -1, 1, 0), i * rates.close),
        ((-1, 1, 0, 0), o * inactivation), ((1, -1, 0, 0), i * rates.recover), ((0, 0, 1, 0), c * inactivation), ((0, 0, -1, 0), ci * rates.recover),
        ((0, 0, 0, 1), where(ions < capacity, (rates.influx + rates.release * o) * capacity + rates.influx_flat)), ((0, 0, 0, -1), where(ions > 0, rates.loss * ions + rates.loss_flat)),
    ]


def _rates(channels: int, capacity: int, rates: Rates) -> list[tuple[tuple[int, int, int, int], Column]]:
    c, o, i, ci, ions = (F.col(x).cast("double") for x in ("closed", "open", "inact", "cinact", "ions"))
    return moves_of(c, o, i, ci, ions, capacity, rates, lambda condition, value: F.when(condition, value).otherwise(0.0))


def release_site_speed(spark: SparkSession, channels: int, capacity: int, rates: Rates = Rates()) -> float:
    """1.02 times the largest total rate out of a state: what the chain is uniformised with. One aggregation."""
    total = sum((r for _, r in _rates(channels, capacity, rates)), F.lit(0.0))
    return 1.02 * release_site_states(spark, channels, capacity).agg(F.max(total)).first()[0]


def release_site_moves(channels: int, capacity: int, speed: float, rates: Rates = Rates()) -> Column:
    """A state's exits as array<struct<dst, prob>>: the uniformised chain's row, made anew at each use."""
    moves = _rates(channels, capacity, rates)
    go = [
        F.struct(state_id(F.col("open") + a, F.col("inact") + b, F.col("cinact") + d, F.col("ions") + e, channels, capacity).alias("dst"), (rate / speed).alias("prob"))
        for (a, b, d, e), rate in moves
    ]
    stay = F.struct(F.col("state").alias("dst"), (1 - sum((rate for _, rate in moves), F.lit(0.0)) / speed).alias("prob"))
    return F.filter(F.array(*go, stay), lambda m: m["prob"] > 0)


def release_site(spark: SparkSession, channels: int, capacity: int, rates: Rates = Rates()) -> DataFrame:
    """Stored edges (src, dst, prob) with composite ids; at most 11 exits a state, generated without a shuffle."""
    return release_site_states(spark, channels, capacity).select(F.col("state").alias("src"), F.inline(release_site_moves(channels, capacity, release_site_speed(spark, channels, capacity, rates), rates)))
