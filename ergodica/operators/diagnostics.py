"""Checks of what the methods assume: one strongly connected, aperiodic component; conserved mass; independent columns."""

from __future__ import annotations

from functools import reduce
from math import gcd

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.work import discard, written
from .block import columns, mass, width_of
from .chain import Chain, detailed_balance
from .extract import tsqr


MERGE_LEVELS = 12


def components(edges: DataFrame, nodes: DataFrame | None = None, rounds: int = 60) -> DataFrame:
    """state, component (least state of it), weakly connected: least labels spread along edges, then labels jump to their
    label's label, so the rounds grow with the logarithm of the diameter."""
    both = edges.select("src", "dst").union(edges.select("dst", "src")).where("src <> dst").distinct()
    both = written(both, "both")
    nodes = nodes if nodes is not None else edges.select(F.col("src").alias("state")).union(edges.select("dst")).distinct()
    lab = written(nodes.select("state", F.col("state").alias("component")), "labels")
    for _ in range(rounds):
        near = both.join(lab.withColumnsRenamed({"state": "dst", "component": "c"}), "dst").groupBy(F.col("src").alias("state")).agg(F.min("c").alias("c"))
        step = lab.join(near, "state", "left").select("state", F.least("component", F.coalesce("c", "component")).alias("component"))
        jump = step.join(step.select(F.col("state").alias("component"), F.col("component").alias("j")), "component", "left").select("state", F.least("component", F.coalesce("j", "component")).alias("component"))
        new = written(jump, "labels")
        moved = new.join(lab.withColumnRenamed("component", "was"), "state").where("component <> was")
        if moved.isEmpty():
            return new
        lab = new
    raise RuntimeError("the components did not settle")


def largest_component(edges: DataFrame) -> DataFrame:
    """state of the largest weak component (ties: the least label)."""
    comp = components(edges)
    best = comp.groupBy("component").count().orderBy(F.desc("count"), "component").limit(1).select("component")
    return comp.join(F.broadcast(best), "component", "left_semi").select("state")


def reach(edges: DataFrame, seeds: DataFrame, rounds: int = 10_000) -> DataFrame:
    """state, level: breadth-first levels from ``seeds`` (state). Each level writes its own states only; what was seen is the union of the levels."""
    levels = [written(seeds.select("state", F.lit(0).alias("level")), "reach")]
    for level in range(1, rounds):
        front = levels[-1].select(F.col("state").alias("src"))
        new = edges.join(front, "src", "left_semi").select(F.col("dst").alias("state")).distinct()
        for known in levels:
            new = new.join(known.select("state"), "state", "left_anti")
        new = written(new.withColumn("level", F.lit(level)), "reach")
        if new.isEmpty():
            return reduce(DataFrame.unionByName, levels)
        levels.append(new)
        if len(levels) > MERGE_LEVELS:  # a long chain of small levels: one table, rewritten once in so many levels
            whole = written(reduce(DataFrame.unionByName, levels[:-1]), "reach")
            discard(*levels[:-1])
            levels = [whole, levels[-1]]
    raise RuntimeError("too many levels")


def strong_components(edges: DataFrame, nodes: DataFrame | None = None, rounds: int = 1000) -> DataFrame:
    """state, component: forward and backward reach from each weak component's least state, then again on the rest."""
    left = nodes if nodes is not None else edges.select(F.col("src").alias("state")).union(edges.select("dst")).distinct()
    left, e, out = written(left, "left"), edges.select("src", "dst").distinct(), None
    for _ in range(rounds):
        if left.isEmpty():
            break
        lone = left.join(e.select(F.col("src").alias("state")), "state", "left_semi").join(e.select(F.col("dst").alias("state")), "state", "left_semi")
        trimmed = written(left.join(lone, "state", "left_anti").select("state", F.col("state").alias("component")), "strong")  # no way in or out
        if not trimmed.isEmpty():
            found = trimmed
        else:
            weak = components(e, left)
            pivots = weak.groupBy("component").agg(F.min("state").alias("state"))
            tag = lambda d: d.join(weak, "state").select("state", "component")
            ahead = tag(reach(e, pivots.select("state")).select("state"))
            back = tag(reach(e.select(F.col("dst").alias("src"), F.col("src").alias("dst")), pivots.select("state")).select("state"))
            found = written(ahead.join(back, ["state", "component"]).groupBy("state").agg(F.min("component").alias("component")), "strong")
        out = found if out is None else written(out.unionByName(found), "strong")
        left = written(left.join(found.select("state"), "state", "left_anti"), "left")
        keep = left.select(F.col("state").alias("src"))
        e = written(e.join(keep, "src", "left_semi").join(keep.withColumnRenamed("src", "dst"), "dst", "left_semi").select("src", "dst"), "edges")
    return out


def period(edges: DataFrame, root: int | None = None) -> int:
    """Greatest common divisor of the cycle lengths of a strongly connected chain (1: aperiodic)."""
    at = root if root is not None else edges.agg(F.min("src")).first()[0]
    levels = reach(edges, edges.sparkSession.createDataFrame([(at,)], "state long"))
    gaps = edges.join(levels.select(F.col("state").alias("src"), F.col("level").alias("a")), "src").join(levels.select(F.col("state").alias("dst"), F.col("level").alias("b")), "dst")
    found = [r[0] for r in gaps.select(F.abs(F.col("a") + 1 - F.col("b"))).distinct().collect()]  # at most the number of levels
    out = 0
    for g in found:
        out = gcd(out, int(g))
    return out


def mass_drift(before: DataFrame, after: DataFrame) -> float:
    return float(max(abs(a - b) for a, b in zip(mass(before), mass(after), strict=True)))


def rank(block: DataFrame, rtol: float = 1e-12) -> int:
    s = np.linalg.svd(tsqr(block, columns(width_of(block))), compute_uv=False)
    return int((s > rtol * s[0]).sum()) if s[0] > 0 else 0


def reversible(chain: Chain, pi: DataFrame, tol: float = 1e-9) -> bool:
    worst = detailed_balance(chain, pi).agg(F.max(F.abs("gap"))).first()[0]
    return (worst or 0.0) <= tol


def check(chain: Chain) -> dict:
    """components, strongly connected, period (0 if not strongly connected)."""
    strong = strong_components(chain.edges, chain.nodes()).select("component").distinct().count()
    return {"strong_components": strong, "irreducible": strong == 1, "period": period(chain.edges) if strong == 1 else 0}
