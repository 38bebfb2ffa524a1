"""Chains: transitions, their states, and the transformations that users of stationary vectors need."""

from __future__ import annotations

from dataclasses import dataclass, replace

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.work import written


@dataclass(frozen=True)
class Chain:
    """edges (src, dst, prob); states (state, label) or None; scalars that need no edges of their own.

    ``follow`` < 1 restarts with ``1 - follow`` at ``preference`` (state, share; None: uniform). ``dangling`` names states
    (state) whose whole mass is spread uniformly. Neither is ever stored as edges. ``size``, the number of states, is counted once by the solvers;
    ``hubs`` (src, salts) belongs to edges with a column ``salt`` (``plans.layout``).
    """

    edges: DataFrame
    states: DataFrame | None = None
    follow: float = 1.0
    preference: DataFrame | None = None
    dangling: DataFrame | None = None
    name: str = "chain"
    size: int | None = None
    hubs: DataFrame | None = None

    def nodes(self) -> DataFrame:
        if self.states is not None:
            return self.states.select("state")
        return self.edges.select(F.col("src").alias("state")).union(self.edges.select("dst")).distinct()

    def labelled(self, pi: DataFrame) -> DataFrame:
        if self.states is None:
            return pi.select("state", F.col("state").cast("string").alias("label"), "pi")
        return pi.join(self.states, "state", "left").select("state", F.col("label").cast("string").alias("label"), "pi")


@dataclass(frozen=True)
class MatrixFreeChain:
    """states (state, ...) and ``moves``, a column array<struct<dst, prob>> made from a state's row at each use; no stored edges."""

    rows: DataFrame
    moves: Column
    name: str = "matrix_free"

    def stored(self) -> Chain:
        return Chain(self.rows.select(F.col("state").alias("src"), F.inline(self.moves)), name=self.name)

    def nodes(self) -> DataFrame:
        return self.rows.select("state")


@dataclass(frozen=True)
class FactoredChain:
    """A step goes through ``factors``, weights (src, dst, w) with repeated pairs, rows scaled to 1 at each use; ``stay`` of the mass remains. Every
    destination has exits in the next factor, the last one's in the first. Nothing is composed, scaled or summed in storage."""

    factors: tuple[DataFrame, ...]
    stay: float = 0.0
    name: str = "factored"

    def stored(self) -> Chain:
        edges = normalise(self.factors[0])
        for f in self.factors[1:]:
            edges = compose(edges, normalise(f))
        chain = Chain(written(edges, "edges"), name=self.name)
        return lazy(chain, 1.0 - self.stay) if self.stay else chain

    def nodes(self) -> DataFrame:
        return self.factors[0].select(F.col("src").alias("state")).distinct()


@dataclass(frozen=True)
class SuccessionChain:
    """sequences (ids: array<long>, the states of a row in their order, the last followed by the first) and states (state, label, visits: how often it is
    met). States that only follow themselves are components of their own and left out. Pairs are counted when the chain is solved."""

    sequences: DataFrame
    states: DataFrame
    name: str = "succession"

    def stored(self) -> Chain:
        after = F.concat(F.slice("ids", F.lit(2), F.size("ids")), F.slice("ids", 1, 1))
        pairs = self.sequences.where(F.size("ids") > 0).select(F.inline(F.arrays_zip(F.col("ids").alias("src"), after.alias("dst"))), F.lit(1.0).alias("w"))
        w = written(pairs.groupBy("src", "dst").agg(F.sum("w").alias("w")), "pairs")
        other = w.where("src <> dst").select("src").distinct()
        states = written(self.states.select("state", "label").join(other.withColumnRenamed("src", "state"), "state", "left_semi"), "states")
        return Chain(written(normalise(w.join(other, "src", "left_semi")), "edges"), states, name=self.name)

    def nodes(self) -> DataFrame:
        return self.states.select("state")

    def labelled(self, pi: DataFrame) -> DataFrame:
        return pi.join(self.states, "state").select("state", "label", "pi")


def encode(edges: DataFrame, src: str = "src", dst: str = "dst", weight: str = "w") -> tuple[DataFrame, DataFrame]:
    """(edges with dense ids, states (state, label)): ids follow the labels' order.

    Labels are range-partitioned and sorted; a partition's ids start after the rows of the partitions before it, whose counts
    (one number each) are all that reaches the driver. No global window.
    """
    labels = edges.select(F.col(src).alias("label")).union(edges.select(F.col(dst))).distinct().where("label is not null")
    placed = written(labels.repartitionByRange("label").sortWithinPartitions("label").withColumn("part", F.spark_partition_id()).withColumn("at", F.monotonically_increasing_id()), "labels")
    counts = sorted((r.part, r.n, r.first) for r in placed.groupBy("part").agg(F.count("*").alias("n"), F.min("at").alias("first")).collect())
    base, offset = [], 0
    for part, n, first in counts:
        base.append((part, offset - first))
        offset += n
    spark = edges.sparkSession
    shift = spark.createDataFrame(base or [(0, 0)], "part int, shift long")
    states = written(placed.join(F.broadcast(shift), "part").select((F.col("at") + F.col("shift")).alias("state"), "label"), "states")
    out = edges.join(states.select(F.col("label").alias(src), F.col("state").alias("__s")), src).join(states.select(F.col("label").alias(dst), F.col("state").alias("__d")), dst)
    return out.select(F.col("__s").alias("src"), F.col("__d").alias("dst"), F.col(weight).alias("w")), states


def normalise(weights: DataFrame, keep_counts: bool = False) -> DataFrame:
    """(src, dst, w) with repeated pairs to (src, dst, prob); zero and null weights are dropped, negative ones rejected by ``validate``."""
    w = weights.where("w is not null and w <> 0").groupBy("src", "dst").agg(F.sum("w").cast("double").alias("w"))
    total = w.groupBy("src").agg(F.sum("w").alias("t"))
    out = w.join(total, "src").select("src", "dst", (F.col("w") / F.col("t")).alias("prob"), "w")
    return out if keep_counts else out.drop("w")


def from_weights(weights: DataFrame, name: str = "chain") -> Chain:
    """Labels and weights to a chain with dense ids."""
    w = weights.where("w is not null and w <> 0").groupBy("src", "dst").agg(F.sum("w").cast("double").alias("w"))
    edges, states = encode(w)
    return Chain(written(normalise(edges), "edges"), states, name=name)


def row_sums(edges: DataFrame) -> DataFrame:
    return edges.groupBy("src").agg(F.sum("prob").alias("total"), F.count("*").alias("exits"), F.min("prob").alias("least"))


def validate(chain: Chain, tol: float = 1e-12) -> dict:
    """Counts of rows whose sum is off, of negative or null probabilities, of states without exits."""
    sums = row_sums(chain.edges)
    r = sums.agg(F.count("*").alias("rows"), F.sum((F.abs(F.col("total") - 1) > tol).cast("long")).alias("off"), F.max(F.abs(F.col("total") - 1)).alias("worst")).first()
    bad = chain.edges.where("prob < 0 or prob is null or isnan(prob) or src is null or dst is null").count()
    return {"rows": r.rows, "off": r.off or 0, "worst": r.worst or 0.0, "bad": bad, "dangling": dangling(chain).count()}


def dangling(chain: Chain) -> DataFrame:
    return chain.nodes().join(chain.edges.select(F.col("src").alias("state")).distinct(), "state", "left_anti")


def fix_dangling(chain: Chain, policy: str = "self_loop") -> Chain:
    """Repairs states without exits: a loop, uniform spreading (a scalar a step, never edges), or dropping them, again and again."""
    if policy == "self_loop":
        loops = dangling(chain).select(F.col("state").alias("src"), F.col("state").alias("dst"), F.lit(1.0).alias("prob"))
        return replace(chain, edges=chain.edges.unionByName(loops))
    if policy == "uniform":
        return replace(chain, states=chain.states if chain.states is not None else _plain(chain.nodes()), dangling=written(dangling(chain), "dangling"))
    if policy == "drop":
        edges, nodes = chain.edges, chain.nodes()
        while True:
            gone = nodes.join(edges.select(F.col("src").alias("state")).distinct(), "state", "left_anti")
            if gone.isEmpty():
                break
            nodes = written(nodes.join(gone, "state", "left_anti"), "nodes")
            edges = written(edges.join(gone.withColumnRenamed("state", "dst"), "dst", "left_anti").select("src", "dst", "prob"), "edges")
        states = None if chain.states is None else chain.states.join(nodes, "state", "left_semi")
        return replace(chain, edges=normalise(edges.withColumnRenamed("prob", "w")), states=states)
    raise ValueError(policy)


def _plain(nodes: DataFrame) -> DataFrame:
    return nodes.select("state", F.col("state").cast("string").alias("label"))


def lazy(chain: Chain, move: float = 0.5) -> Chain:
    """(1 - move) I + move P: aperiodic, with the same stationary vector."""
    stay = chain.nodes().select(F.col("state").alias("src"), F.col("state").alias("dst"), F.lit(1.0 - move).alias("prob"))
    scaled = chain.edges.select("src", "dst", (F.col("prob") * move).alias("prob"))
    return replace(chain, edges=scaled.unionByName(stay).groupBy("src", "dst").agg(F.sum("prob").alias("prob")))


def teleport(chain: Chain, follow: float = 0.85, preference: DataFrame | None = None) -> Chain:
    """Restart with probability ``1 - follow`` at ``preference`` (state, share), by default anywhere."""
    return replace(chain, follow=follow, preference=preference, states=chain.states if chain.states is not None else _plain(chain.nodes()))


def restrict(chain: Chain, keep: DataFrame) -> Chain:
    """The chain on the states of ``keep``, rows scaled to 1 again."""
    e = chain.edges.join(keep.select(F.col("state").alias("src")), "src", "left_semi").join(keep.select(F.col("state").alias("dst")), "dst", "left_semi")
    states = None if chain.states is None else chain.states.join(keep, "state", "left_semi")
    return replace(chain, edges=normalise(e.select("src", "dst", F.col("prob").alias("w"))), states=states)


def compose(a: DataFrame, b: DataFrame) -> DataFrame:
    """The edges of the product: a step by ``a``, then one by ``b``."""
    right = b.select(F.col("src").alias("dst"), F.col("dst").alias("end"), F.col("prob").alias("p"))
    return a.join(right, "dst").groupBy("src", F.col("end").alias("dst")).agg(F.sum(F.col("prob") * F.col("p")).alias("prob"))


def power_of_two(edges: DataFrame, doublings: int) -> DataFrame:
    """The edges of P to the power 2^doublings (small chains: it fills in)."""
    for _ in range(doublings):
        edges = written(compose(edges, edges), "power")
    return edges


def reverse(chain: Chain, pi: DataFrame) -> DataFrame:
    """Edges of the time-reversed chain: pi_j P_ji / pi_i; pi: state, pi."""
    at = lambda c, p: pi.select(F.col("state").alias(c), F.col("pi").alias(p))
    flow = chain.edges.join(at("src", "p_src"), "src").join(at("dst", "p_dst"), "dst")
    return flow.select(F.col("dst").alias("src"), F.col("src").alias("dst"), (F.col("p_src") * F.col("prob") / F.col("p_dst")).alias("prob"))


def detailed_balance(chain: Chain, pi: DataFrame) -> DataFrame:
    """src, dst, gap = pi_src P_src,dst - pi_dst P_dst,src for every pair with a transition either way."""
    flow = chain.edges.join(pi.select(F.col("state").alias("src"), "pi"), "src").select("src", "dst", (F.col("pi") * F.col("prob")).alias("flow"))
    both = flow.unionByName(flow.select(F.col("dst").alias("src"), F.col("src").alias("dst"), (-F.col("flow")).alias("flow")))
    return both.groupBy("src", "dst").agg(F.sum("flow").alias("gap"))


def arrow_edges(edges: DataFrame) -> pa.Table:
    """A small chain's edges on the driver (diagnostics of small chains and tests)."""
    return edges.select("src", "dst", "prob").toArrow()
