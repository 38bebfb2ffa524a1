"""Functions to register: scalar SQL, aggregate (grouped pandas), and table functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators.kernel import solve_arrays


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def norm2(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def axpy(c: Column | float, a: Column, b: Column) -> Column:
    """c a + b on arrays of doubles."""
    k = c if isinstance(c, Column) else F.lit(float(c))
    return F.zip_with(a, b, lambda x, y: k * x + y)


@F.pandas_udf(T.DoubleType())
def combine(x: pd.Series, c: pd.Series) -> pd.Series:
    """A basis row (array) times small coefficients (array)."""
    return pd.Series((np.stack(x.to_numpy()) * np.stack(c.to_numpy())).sum(axis=1)) if len(x) else pd.Series([], dtype=float)


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def stationary_of(src: pd.Series, dst: pd.Series, w: pd.Series) -> np.ndarray:
    """Grouped aggregate: the stationary vector of a small group's weights, by rising state."""
    s, d, x = src.to_numpy(np.int64), dst.to_numpy(np.int64), w.to_numpy(np.float64)
    names = np.unique(np.concatenate([s, d]))
    total = np.bincount(np.searchsorted(names, s), x, len(names))
    prob = x / total[np.searchsorted(names, s)]
    order = np.lexsort((d, s))
    return solve_arrays(s[order], d[order], prob[order], width=min(4, len(names)), check_every=5, max_iter=20_000).pi


class Stationary:
    """TABLE(src, dst, w) PARTITION BY a key, width, depth, tol -> (state, pi, iterations, residual, chain_id).

    ``chain_id`` is the partition's column of this name; null for a table without one.
    """

    def __init__(self) -> None:
        self.rows: list[tuple[int, int, float]] = []
        self.options: tuple[int, int, float] = (4, 1, 1e-10)
        self.chain: int | None = None

    def eval(self, row, width: int, depth: int, tol: float):
        self.rows.append((row["src"], row["dst"], float(row["w"])))
        self.options = (width, depth, tol)
        self.chain = row["chain_id"] if "chain_id" in row else None

    def terminate(self):
        if not self.rows:
            return
        t = pd.DataFrame(self.rows, columns=["src", "dst", "w"]).groupby(["src", "dst"], as_index=False).w.sum()
        prob = t.w / t.groupby("src").w.transform("sum")
        width, depth, tol = self.options
        n = len(set(t.src) | set(t.dst))
        r = solve_arrays(t.src.to_numpy(np.int64), t.dst.to_numpy(np.int64), prob.to_numpy(), width=min(width, n), depth=depth, tol=tol, check_every=5)
        for s, p in zip(r.states.tolist(), r.pi.tolist(), strict=True):
            yield s, p, r.ledger.iterations, float(r.residual), self.chain


class ReleaseSiteMoves:
    """(closed, open, inact, cinact, ions, channels, capacity, speed) -> (dst, prob): a state's exits at the default rates.

    A surface for SQL, row by row in Python; ``synthetic.release_site_moves`` is the same as an expression, for anything large.
    """

    def eval(self, closed: int, open_: int, inact: int, cinact: int, ions: int, channels: int, capacity: int, speed: float):
        from ..sources.synthetic import Rates, moves_of

        b = channels + 1
        moves = moves_of(closed, open_, inact, cinact, ions, capacity, Rates(), lambda condition, value: value if condition else 0.0)
        stay = 1 - sum(rate for _, rate in moves) / speed
        for (a, c, d, e), p in [(m, rate / speed) for m, rate in moves] + [((0, 0, 0, 0), stay)]:
            if p > 0:
                yield (((open_ + a) * b + inact + c) * b + cinact + d) * (capacity + 1) + ions + e, p


def register(spark: SparkSession) -> None:
    """predicted_steps and saving (SQL), combine, stationary_of, and the table functions."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION predicted_steps(modulus DOUBLE, tol DOUBLE) RETURNS DOUBLE RETURN ln(tol) / ln(modulus)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION matvec_saving(base DOUBLE, other DOUBLE) RETURNS DOUBLE RETURN 100 * (1 - other / base)")
    spark.udf.register("combine", combine)
    spark.udf.register("stationary_of", stationary_of)
    spark.udtf.register("stationary", F.udtf(Stationary, returnType="state bigint, pi double, iterations bigint, residual double, chain_id bigint"))
    spark.udtf.register("release_site_moves", F.udtf(ReleaseSiteMoves, returnType="dst bigint, prob double"))
