"""What a solve costs: steps, passes, matrix-vector products, extractions, storage."""

from __future__ import annotations

from dataclasses import asdict, dataclass, replace

from pyspark.sql import Observation
from pyspark.sql import functions as F

from .chain import Chain


@dataclass
class CostLedger:
    iterations: int = 0
    passes: int = 0  # scans of the transitions, verification and explicit images included
    matvecs_core: int = 0  # iterations times width
    matvecs_all: int = 0  # explicit images and verification passes too
    extractions: int = 0
    extraction_seconds: float = 0.0
    seconds: float = 0.0

    def step(self, width: int, many: int = 1, scans: int = 1) -> None:
        """``many`` steps of a block; ``scans``: of the transitions in one step, more than one where columns go by themselves or in chunks."""
        self.iterations += many
        self.passes += many * scans
        self.matvecs_core += many * width
        self.matvecs_all += many * width

    def extra_pass(self, columns: int, scans: int = 1) -> None:
        self.passes += scans
        self.matvecs_all += columns

    def as_dict(self) -> dict:
        return asdict(self)


def saving(base: int, other: int) -> float:
    """Per cent fewer than the base."""
    return 100.0 * (1.0 - other / base)


def storage(n: int, width: int, depth: int = 1) -> int:
    """Doubles kept between steps."""
    return n * width * depth


def decomposition(n: int, width: int, depth: int = 1) -> int:
    """Operations of one extraction, up to a constant."""
    m = width * depth
    return n * m * m + m**3


def observed(chain: Chain) -> tuple[Chain, Observation]:
    """The chain whose edge scan counts its rows, to check the ledger's passes: rows seen = passes times edges."""
    seen = Observation()
    return replace(chain, edges=chain.edges.observe(seen, F.count(F.lit(1)).alias("edges"))), seen
