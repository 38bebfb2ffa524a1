"""How far two distributions are apart, and exact references for small chains."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .results import prefix_sums


def compare(pi: DataFrame, truth: DataFrame, top: int = 10) -> DataFrame:
    """One row: l1, l2, max_abs, total_variation, spearman, top_overlap of two tables (state, pi)."""
    both = pi.select("state", F.col("pi").alias("a")).join(truth.select("state", F.col("pi").alias("b")), "state", "full_outer").select("state", F.coalesce("a", F.lit(0.0)).alias("a"), F.coalesce("b", F.lit(0.0)).alias("b"))
    d = F.col("a") - F.col("b")
    errors = both.agg(F.sum(F.abs(d)).alias("l1"), F.sqrt(F.sum(d * d)).alias("l2"), F.max(F.abs(d)).alias("max_abs"), (F.sum(F.abs(d)) / 2).alias("total_variation"))
    best = lambda c: both.orderBy(F.desc(c), "state").limit(top).select("state")
    overlap = best("a").intersect(best("b")).agg((F.count("*") / top).alias("top_overlap"))
    return errors.crossJoin(overlap).crossJoin(rank_correlation(both))  # one row each


def rank_correlation(both: DataFrame) -> DataFrame:
    """Spearman's correlation of a and b, with mean ranks for ties: values are counted once each and ranked by range partitions."""

    def ranked(c: str) -> DataFrame:
        counts = both.groupBy(c).agg(F.count("*").cast("double").alias("n"))
        return prefix_sums(counts, "n", F.desc(c)).select(c, (F.col("running") - (F.col("n") - 1) / 2).alias(f"r_{c}"))

    return both.join(ranked("a"), "a").join(ranked("b"), "b").agg(F.corr("r_a", "r_b").alias("spearman"))


def dense_reference(edges: DataFrame) -> dict[int, float]:
    """The stationary vector of a small chain by a bordered linear solve."""
    t = edges.select("src", "dst", "prob").toArrow()
    src, dst, prob = (t.column(c).to_numpy() for c in ("src", "dst", "prob"))
    names = np.unique(np.concatenate([src, dst]))
    n = len(names)
    a = np.zeros((n + 1, n))
    np.add.at(a, (np.searchsorted(names, dst), np.searchsorted(names, src)), prob)
    a[:n] -= np.eye(n)
    a[n] = 1
    pi = np.linalg.lstsq(a, np.append(np.zeros(n), 1.0), rcond=None)[0]
    return dict(zip(names.tolist(), pi.tolist(), strict=True))


def visit_share(edges_w: DataFrame, by: str = "src") -> DataFrame:
    """Closed form for cyclic successions and undirected weights: the share of the weight that leaves each state."""
    w = edges_w.groupBy(F.col(by).alias("state")).agg(F.sum("w").alias("w"))
    return w.crossJoin(F.broadcast(w.agg(F.sum("w").alias("t")))).select("state", (F.col("w") / F.col("t")).alias("pi"))


def birth_death_pi(states: int, up: float, down: float) -> np.ndarray:
    p = (up / down) ** np.arange(states)
    return p / p.sum()
