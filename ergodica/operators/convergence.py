"""Residuals, distances between spans, rates."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .chain import Chain, MatrixFreeChain
from .step import propagate


@dataclass(frozen=True)
class ResidualStop:
    tol: float = 1e-10

    def __call__(self, residual: float) -> bool:
        return residual < self.tol


def residual_table(chain: Chain | MatrixFreeChain, v: DataFrame) -> DataFrame:
    """One row: residual = ||P^T v - v|| / ||v||; v: state, x0 (any scale)."""
    moved = propagate(chain, v, probabilities=False).withColumnRenamed("x0", "y")
    both = v.join(moved, "state", "full_outer").select(F.coalesce("x0", F.lit(0.0)).alias("x"), F.coalesce("y", F.lit(0.0)).alias("y"))
    d = F.col("y") - F.col("x")
    return both.agg((F.sqrt(F.sum(d * d)) / F.sqrt(F.sum(F.col("x") * F.col("x")))).alias("residual"))


def residual(chain: Chain | MatrixFreeChain, v: DataFrame) -> float:
    return float(residual_table(chain, v).first()[0])


def span_distance_table(u: DataFrame, v: DataFrame, x: str = "pi") -> DataFrame:
    """One row: distance = sine of the angle between two vectors (state, x), computed without cancellation."""
    both = u.select("state", F.col(x).alias("a")).join(v.select("state", F.col(x).alias("b")), "state", "full_outer").select("state", F.coalesce("a", F.lit(0.0)).alias("a"), F.coalesce("b", F.lit(0.0)).alias("b"))
    a, b = F.col("a"), F.col("b")
    dots = both.agg(F.sum(a * a).alias("aa"), F.sum(b * b).alias("bb"), F.sum(a * b).alias("ab"))
    off = a / F.sqrt("aa") - b / F.sqrt("bb") * (F.col("ab") / F.sqrt(F.col("aa") * F.col("bb")))
    return both.crossJoin(F.broadcast(dots)).agg(F.sqrt(F.sum(off * off)).alias("distance"))  # dots: one row


def span_distance(u: DataFrame, v: DataFrame, x: str = "pi") -> float:
    return float(span_distance_table(u, v, x).first()[0])


def predicted_iterations(modulus: float, tol: float = 1e-10) -> float:
    """Steps until ``modulus^k`` is ``tol``."""
    return 1.0 if modulus <= 0 else math.inf if modulus >= 1 else math.log(tol) / math.log(modulus)


def observed_rate(log: DataFrame) -> DataFrame:
    """chain, method, width, depth, slope of ln(residual) by iteration, and the modulus it stands for."""
    by = ["chain", "method", "width", "depth"]
    slope = F.regr_slope(F.ln("residual"), F.col("iteration").cast("double"))
    return log.where("residual > 0").groupBy(*by).agg(slope.alias("slope")).withColumn("modulus", F.exp("slope"))
