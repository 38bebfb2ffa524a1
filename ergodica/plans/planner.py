"""Which engine, join and width a solve gets."""

from __future__ import annotations

from ..operators.chain import Chain, MatrixFreeChain

LOCAL_EDGES = 5_000_000  # edges a single task solves in numpy (some 120 MB)
BROADCAST_BYTES = 256 << 20  # of a block; beyond it edges and block meet by shuffle


def choose_engine(chain: Chain | MatrixFreeChain, budget: int = LOCAL_EDGES) -> str:
    """local if a counted bound says that the chain fits a task; the count stops at the budget."""
    edges = chain.stored().edges if isinstance(chain, MatrixFreeChain) else chain.edges
    return "local" if edges.limit(budget + 1).count() <= budget else "distributed"


def block_bytes(states: int, width: int) -> int:
    return states * (8 * width + 16)


def choose_join(states: int, width: int, limit: int = BROADCAST_BYTES) -> str | None:
    """'broadcast' while the block's size is within the limit, else 'shuffle_hash' on edges laid out by source."""
    return "broadcast" if block_bytes(states, width) <= limit else "shuffle_hash"


def choose_width(table: list[dict], seconds_a_pass: float, seconds_a_matvec: float) -> int:
    """The width with the least predicted time when a pass costs so much and each column adds so much."""
    return min(table, key=lambda r: r["steps"] * (seconds_a_pass + r["width"] * seconds_a_matvec))["width"]
