"""Blocks of probability columns: DataFrames state, x0 .. x{s-1}, a state's values side by side."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

MANTISSA = float(1 << 53)


def columns(width: int) -> list[str]:
    return [f"x{j}" for j in range(width)]


def width_of(block: DataFrame) -> int:
    return len([c for c in block.columns if c.startswith("x") and c[1:].isdigit()])


def uniform(state: Column, column: int, seed: int) -> Column:
    """A number in (0, 1) that depends on state, column and seed only: the same on every run, partitioning and retry."""
    return (F.shiftrightunsigned(F.xxhash64(state, F.lit(column), F.lit(seed)), 11).cast("double") + 0.5) / MANTISSA


def start(states: DataFrame, width: int = 1, seed: int = 0, kind: str = "random") -> DataFrame:
    """``width`` linearly independent probability columns.

    random: hash-uniform entries; indicator: disjoint groups of states. One small aggregation gives the totals.
    """
    s = F.col("state")
    if kind == "random":
        raw = [uniform(s, j, seed) for j in range(width)]
    elif kind == "indicator":
        raw = [F.when(F.pmod(F.xxhash64(s, F.lit(seed)), F.lit(width)) == j, 1.0).otherwise(0.0) for j in range(width)]
    else:
        raise ValueError(kind)
    block = states.select("state", *(r.alias(c) for r, c in zip(raw, columns(width), strict=True)))
    return scaled(block)


def scaled(block: DataFrame) -> DataFrame:
    """Each column divided by its total."""
    cols = columns(width_of(block))
    totals = block.agg(*(F.sum(c).alias(c) for c in cols)).first()
    return block.select("state", *((F.col(c) / F.lit(totals[c] or 1.0)).alias(c) for c in cols))


def user_start(states: DataFrame, given: DataFrame) -> DataFrame:
    """Columns x0 .. of ``given`` (state, x0 ..) on all states, missing ones 0, scaled to total 1."""
    cols = columns(width_of(given))
    return scaled(states.select("state").join(given, "state", "left").select("state", *(F.coalesce(c, F.lit(0.0)).alias(c) for c in cols)))


def warm_start(states: DataFrame, width: int, seed: int, given: DataFrame) -> DataFrame:
    """``start`` with as many first columns as ``given`` (state, x0 ..) has replaced by its own, scaled to total 1; a column of zeros stays random."""
    some = user_start(states, given)
    names = columns(min(width, width_of(given)))
    if any(m == 0 for m in mass(some, names)):
        return start(states, width, seed)
    both = start(states, width, seed).drop(*names).join(some.select("state", *names), "state")
    return both.select("state", *columns(width))


def start_orthonormal(states: DataFrame, width: int, seed: int = 0) -> DataFrame:
    from .extract import combine, tsqr

    import numpy as np

    block = start(states, width, seed)
    for _ in range(2):
        r = tsqr(block, columns(width))
        block = combine(block, np.linalg.inv(r), columns(width))
    return block


def to_long(block: DataFrame) -> DataFrame:
    """state, column, x."""
    cols = columns(width_of(block))
    return block.unpivot("state", cols, "name", "x").select("state", F.substring("name", 2, 9).cast("int").alias("column"), "x")


def to_wide(long: DataFrame, width: int) -> DataFrame:
    return long.groupBy("state").pivot("column", list(range(width))).agg(F.sum("x")).select("state", *(F.coalesce(F.col(f"`{j}`"), F.lit(0.0)).alias(f"x{j}") for j in range(width)))


def mass(block: DataFrame, cols: list[str] | None = None) -> list[float]:
    r = block.agg(*(F.sum(c).alias(c) for c in cols or columns(width_of(block)))).first()
    return [float(x or 0.0) for x in r]
