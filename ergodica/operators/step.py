"""One pass: a block pushed along the transitions, ``P^T X``.

One join of edges and block on the source and one hash aggregation by destination, in whole-stage code: the partial sums
are made before the only shuffle. Restarts and dangling mass are rows of the same aggregation, never edges. A block within
``planner.BROADCAST_BYTES`` is broadcast; beyond that, edges laid out by ``plans.layout.laid_out`` stay where they are and only blocks travel.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .block import columns, mass, width_of
from .chain import Chain, MatrixFreeChain

CHUNK = 32  # columns of one generated method; wider blocks go in chunks, each with a scan of its own


def scans(width: int, layout: str = "rows") -> int:
    """Scans of the transitions in one step."""
    return width if layout == "columns" else -(-width // CHUNK)


def propagate(chain: Chain | MatrixFreeChain, block: DataFrame, join: str | None = None, cols: list[str] | None = None, probabilities: bool = True) -> DataFrame:
    """The block one step on. A state without a row has zeros: nothing enters it.

    ``probabilities`` False: columns of any total (orthonormal bases, unit vectors); a restarting chain then sums them first.
    """
    cols = cols or columns(width_of(block))
    if len(cols) > CHUNK:
        parts = [propagate(chain, block.select("state", *cols[a : a + CHUNK]), join, cols[a : a + CHUNK], probabilities) for a in range(0, len(cols), CHUNK)]
        wide = reduce(lambda x, y: x.join(y, "state", "full_outer"), parts)
        return wide.select("state", *(F.coalesce(c, F.lit(0.0)).alias(c) for c in cols))
    if isinstance(chain, MatrixFreeChain):
        flow = chain.rows.join(block.hint(join) if join else block, "state").select(*cols, F.inline(chain.moves))
        return _summed(flow.select(F.col("dst").alias("state"), *((F.col("prob") * F.col(c)).alias(c) for c in cols)), cols)
    side = block.select(F.col("state").alias("src"), *cols)
    keys = ["src"]
    if chain.hubs is not None:
        side, keys = salted_block(side, chain.hubs), ["src", "salt"]
    flow = chain.edges.join(side.hint(join) if join else side, keys)
    out = flow.select(F.col("dst").alias("state"), *((F.col("prob") * F.col(c) * chain.follow if chain.follow < 1.0 else F.col("prob") * F.col(c)).alias(c) for c in cols))
    for more in _given(chain, block, cols, [1.0] * len(cols) if probabilities or chain.follow == 1.0 else mass(block, cols)):
        out = out.unionByName(more)
    return _summed(out, cols)


def _summed(flow: DataFrame, cols: list[str]) -> DataFrame:
    return flow.groupBy("state").agg(*(F.sum(c).alias(c) for c in cols))


def salted_block(side: DataFrame, hubs: DataFrame) -> DataFrame:
    """Rows of hubs (src, salts: fewer than there are partitions, see ``plans.layout``) once for each salt, others with salt 0."""
    marked = side.join(F.broadcast(hubs), "src", "left")
    return marked.withColumn("salt", F.explode(F.sequence(F.lit(0), F.coalesce(F.col("salts") - 1, F.lit(0))))).drop("salts")


def _given(chain: Chain, block: DataFrame, cols: list[str], total: list[float]) -> list[DataFrame]:
    """What states get that no edge brings: a share of the mass on dangling states (one number a column), and of the restarts."""
    out = []
    if chain.dangling is not None or (chain.follow < 1.0 and chain.preference is None):
        n = chain.size or chain.nodes().count()
    if chain.dangling is not None:
        lost = block.join(chain.dangling, "state", "left_semi").agg(*((F.coalesce(F.sum(c), F.lit(0.0)) * (chain.follow / n)).alias(c) for c in cols))
        out.append(chain.nodes().crossJoin(F.broadcast(lost)))  # one row
    if chain.follow < 1.0:
        share = F.lit((1.0 - chain.follow) / n) if chain.preference is None else F.col("share") * (1.0 - chain.follow)
        at = chain.nodes() if chain.preference is None else chain.preference
        out.append(at.select("state", *((share * t).alias(c) for c, t in zip(cols, total, strict=True))))
    return out


def advance(chain: Chain | MatrixFreeChain, block: DataFrame, steps: int, join: str | None = None) -> DataFrame:
    """``steps`` passes in one plan."""
    for _ in range(steps):
        block = propagate(chain, block, join)
    return block


def propagate_columns(chain: Chain, block: DataFrame) -> DataFrame:
    """The loosely coupled layout: every column evolves by itself, with a scan of its own; same result as ``propagate``."""
    parts = [propagate(chain, block.select("state", F.col(c).alias("x0"))).withColumnRenamed("x0", c) for c in columns(width_of(block))]
    wide = reduce(lambda x, y: x.join(y, "state", "full_outer"), parts)
    return wide.select("state", *(F.coalesce(c, F.lit(0.0)).alias(c) for c in columns(width_of(block))))
