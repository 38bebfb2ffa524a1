"""SQL surface: temporary views chain, states, stationary."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..operators.chain import Chain
from .udfs import register as register_functions


def register(spark: SparkSession, chain: Chain, pi: DataFrame | None = None, prefix: str = "") -> None:
    register_functions(spark)
    chain.edges.createOrReplaceTempView(f"{prefix}chain")
    (chain.states if chain.states is not None else chain.nodes()).createOrReplaceTempView(f"{prefix}states")
    if pi is not None:
        pi.createOrReplaceTempView(f"{prefix}stationary")
