"""The whole solve of a chain that fits one task, in numpy: what makes 10^5 and more steps feasible.

Same methods, same small problems as the distributed solvers. A batch of chains is solved by ``applyInArrow`` on chain_id.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import smalldense
from .cost import CostLedger

DENSE = 1200  # states up to which steps are dense products (and runs of steps one product)
SLOTS = 16  # entries of one row of a gather list
CACHE_DOUBLES = 1 << 15  # of a partial sum
TASK_EDGES = 50_000_000  # transitions that one task may hold (some 1.2 GB)


@dataclass
class LocalResult:
    states: np.ndarray
    pi: np.ndarray
    converged: bool
    residual: float
    rank: int
    ledger: CostLedger
    log: list[dict] = field(default_factory=list)
    least: float = 0.0  # the smallest entry before clipping


class Slots:
    """Gather lists of a sparse ``P^T``: states are grouped by their number of entries, so a group's sums are a few whole-array
    products, a slot at a time; a state with more than ``SLOTS`` entries has several rows, summed at the end.

    A column of a block then costs no more than a lone vector: rows of the block are read whole, and partial sums stay in cache.
    """

    def __init__(self, src: np.ndarray, dst: np.ndarray, prob: np.ndarray, n: int):
        order = np.argsort(dst, kind="stable")
        src, prob, dst = src[order], prob[order], dst[order]
        many = np.bincount(dst, minlength=n)
        rows = -(-many // SLOTS)
        self.n, self.first = n, np.cumsum(rows) - rows
        at = np.arange(len(dst)) - (np.cumsum(many) - many)[dst]
        row = self.first[dst] + at // SLOTS
        state = np.repeat(np.arange(n), rows)
        size = np.bincount(row, minlength=len(state))
        start = np.cumsum(size) - size
        hubs = rows > 1
        self.hubs = np.flatnonzero(hubs)
        place = np.where(hubs[state], -1, state)
        spot = np.cumsum(hubs[state]) - 1  # of a hub's row among such rows
        self.extra, self.heads = int(hubs[state].sum()), spot[self.first[self.hubs]] if len(self.hubs) else np.zeros(0, np.int64)
        self.groups = []
        for k in range(1, SLOTS + 1):
            of_size = np.flatnonzero(size == k)
            for own, to in ((of_size[place[of_size] >= 0], place), (of_size[place[of_size] < 0], spot)):
                if len(own):
                    idx = start[own][None, :] + np.arange(k)[:, None]
                    self.groups.append((to is spot, to[own], np.ascontiguousarray(src[idx]), np.ascontiguousarray(prob[idx])))
        self.src, self.prob, self.flow = src, prob, np.empty(len(prob))
        self.entered = np.flatnonzero(many)
        self.starts = (np.cumsum(many) - many)[self.entered]

    def step(self, x: np.ndarray) -> np.ndarray:
        width = x.shape[1]
        if width <= 8:  # lone vectors, one after the other
            out = np.zeros((self.n, width))
            for j, v in enumerate(np.ascontiguousarray(x.T)):
                np.take(v, self.src, out=self.flow, mode="clip")
                self.flow *= self.prob
                out[self.entered, j] = np.add.reduceat(self.flow, self.starts) if len(self.starts) else 0.0
            return out
        out, part = np.zeros((self.n, width)), np.empty((self.extra, width))
        chunk = max(64, CACHE_DOUBLES // width)
        gathered, total = np.empty((chunk, width)), np.empty((chunk, width))
        for hub, to, src, prob in self.groups:
            target = part if hub else out
            for a in range(0, len(to), chunk):
                b = min(a + chunk, len(to))
                t, g = total[: b - a], gathered[: b - a]
                for j in range(len(src)):
                    into = g if j else t
                    np.take(x, src[j, a:b], axis=0, out=into, mode="clip")
                    into *= prob[j, a:b, None]
                    if j:
                        t += g
                target[to[a:b]] = t
        if self.extra:
            out[self.hubs] = np.add.reduceat(part, self.heads, axis=0)
        return out


class Operator:
    """``P^T`` on row blocks, states numbered 0 .. n-1, with restarts at ``preference`` (by default anywhere) and ``dangling`` states, whose mass is spread over all."""

    def __init__(self, src: np.ndarray, dst: np.ndarray, prob: np.ndarray, n: int, follow: float = 1.0, preference: np.ndarray | None = None, dangling: np.ndarray | None = None):
        self.n, self.follow = n, follow
        self.preference = np.full(n, 1 / n) if preference is None else preference
        self.dangling = np.flatnonzero(dangling) if dangling is not None else np.zeros(0, np.int64)
        self.dense = None
        if n <= DENSE:
            self.dense = np.zeros((n, n))
            np.add.at(self.dense, (dst, src), prob)
            self.dense[:, self.dangling] += 1 / n
            if follow < 1:
                self.dense = follow * self.dense + (1 - follow) * self.preference[:, None]
            self.runs: dict[int, np.ndarray] = {}
        else:
            self.slots = Slots(src, dst, prob, n)

    def step(self, x: np.ndarray) -> np.ndarray:
        if self.dense is not None:
            return self.dense @ x
        out = self.slots.step(x)
        if len(self.dangling):
            out += x[self.dangling].sum(axis=0) / self.n
        return out if self.follow == 1 else self.follow * out + (1 - self.follow) * self.preference[:, None] * x.sum(axis=0)

    def run(self, x: np.ndarray, steps: int) -> np.ndarray:
        """``steps`` steps; dense chains take them as one product once the power is known."""
        if self.dense is None or steps < 4 or self.n > 400:
            for _ in range(steps):
                x = self.step(x)
            return x
        if steps not in self.runs:
            self.runs[steps] = np.linalg.matrix_power(self.dense, steps)
        return self.runs[steps] @ x


def start_block(n: int, width: int, seed: int = 0, kind: str = "random") -> np.ndarray:
    if kind == "indicator":
        x = (np.arange(n)[:, None] % width == np.arange(width)[None, :]).astype(float)
    else:
        x = np.random.default_rng(seed).random((n, width))
    return x / np.maximum(x.sum(axis=0), 1e-300)


def solve_arrays(
    src: np.ndarray, dst: np.ndarray, prob: np.ndarray, width: int = 1, depth: int = 1, tol: float = 1e-10, check_every: int | str = 10, max_iter: int = 200_000,
    seed: int = 0, start: np.ndarray | str = "random", extract: str = "min_residual", image: str | None = None, rank_rtol: float = smalldense.RANK_RTOL,
    follow: float = 1.0, states: np.ndarray | None = None, method: str = "block", chain: str = "chain", truth: np.ndarray | None = None,
    preference: np.ndarray | None = None, dangling: np.ndarray | None = None, on_limit: str = "return", op: Operator | None = None,
) -> LocalResult:
    """Power (width 1, depth 1), block, window and window-block methods; stops on the residual, or on the distance to ``truth`` if given.

    ``method='subspace'`` orthonormalises after every step (the general method). ``image``: see ``smalldense.image_of``. ``preference`` (shares)
    and ``dangling`` (marks) follow the rising states. ``on_limit='raise'`` raises where ``max_iter`` steps are not enough. ``op`` steps in place of the edges (``packed``).
    """
    began = time.perf_counter()
    image = smalldense.image_of(extract, image)
    found = np.unique(np.concatenate([src, dst])) if states is None else np.sort(states)
    n = len(found)
    op = op or Operator(np.searchsorted(found, src), np.searchsorted(found, dst), prob, n, follow, preference, dangling)
    x = start_block(n, width, seed, start) if isinstance(start, str) else start
    ledger, log = CostLedger(), []
    every, ring, k, converged = check_every if isinstance(check_every, int) else 4, [x], 0, False
    ext, v = None, x[:, 0]
    while k < max_iter:
        steps = min(every, max_iter - k)
        lone = max(0, steps - depth) if method != "subspace" else 0
        if lone:
            x = op.run(x, lone)
            ring = [x]
        for _ in range(steps - lone):
            x = op.step(x)
            if method == "subspace":
                x, _ = np.linalg.qr(x)
            ring = [*ring[-depth:], x]
        k += steps
        ledger.step(width, steps)
        t = time.perf_counter()
        if method == "subspace" or image == "explicit":
            basis = smalldense.orthonormal(np.hstack(ring[-depth:]), rank_rtol)
            moved = op.step(basis)
            ledger.extra_pass(basis.shape[1])
        else:
            basis, moved = (w[0] if len(w) == 1 else np.hstack(w) for w in (ring[:-1], ring[1:]))
        ext = smalldense.extract(basis, moved, extract, rank_rtol)
        v = basis @ ext.coefficients
        size = np.linalg.norm(v)
        v = v / size if size > 0 else v
        ledger.extractions += 1
        res = ext.residual
        if res < tol or truth is not None:  # verify on the vector itself
            res = float(np.linalg.norm(op.step(v[:, None])[:, 0] - v))
            ledger.extra_pass(1)
        measure = res
        if truth is not None:
            u = truth / np.linalg.norm(truth)
            measure = float(np.linalg.norm(v - u * (u @ v)))
        ledger.extraction_seconds += time.perf_counter() - t
        log.append({"chain": chain, "method": method, "width": width, "depth": depth, "iteration": k, "passes": ledger.passes, "matvecs": ledger.matvecs_core, "residual": measure, "ritz_re": ext.ritz.real, "ritz_im": ext.ritz.imag, "rank": ext.rank, "seconds": time.perf_counter() - began})
        if measure < tol:
            converged = True
            break
        if check_every == "adaptive":
            every = _next_check(log, tol, k)
    if not converged and on_limit == "raise":
        raise RuntimeError(f"{chain}: no convergence in {k} steps, residual {log[-1]['residual'] if log else 1.0:.3g}")
    total = v.sum()
    pi = v / total if abs(total) > 1e-300 else np.full(n, 1 / n)
    least = float(pi.min())
    pi = np.clip(pi, 0, None)
    ledger.seconds = time.perf_counter() - began
    return LocalResult(found, pi / pi.sum(), converged, log[-1]["residual"] if log else 1.0, ext.rank if ext else 1, ledger, log, least)


def _next_check(log: list[dict], tol: float, k: int) -> int:
    """Steps to the predicted crossing from the last two residuals, doubling at most."""
    if len(log) > 1 and log[-1]["residual"] < log[-2]["residual"]:
        rate = (np.log(log[-1]["residual"]) - np.log(log[-2]["residual"])) / (log[-1]["iteration"] - log[-2]["iteration"])
        return int(np.clip((np.log(tol) - np.log(log[-1]["residual"])) / rate, 4, k))
    return max(4, k)


def task_edges(t: pa.Table) -> list[np.ndarray]:
    """src, dst, prob of a chain that one task holds; chains beyond the bound are for the distributed solvers."""
    if t.num_rows > TASK_EDGES:
        raise ValueError(f"{t.num_rows} transitions are more than one task takes ({TASK_EDGES})")
    return [t.column(c).to_numpy() for c in ("src", "dst", "prob")]


def solve_batch(edges: DataFrame, by: str = "chain_id", **options) -> DataFrame:
    """Edges with a chain column to (by, state, pi, iterations, residual): one task solves a chain from start to end.

    Raises where ``max_iter`` steps are not enough (``on_limit='return'``: see the residual), and if a chain has more than ``TASK_EDGES`` edges.
    """
    options = {"on_limit": "raise"} | options
    kind = edges.schema[by].dataType.simpleString()

    def one(t: pa.Table) -> pa.Table:
        src, dst, prob = task_edges(t)
        r = solve_arrays(src, dst, prob, **options)
        n = len(r.states)
        return pa.table([pa.array([t.column(by)[0].as_py()] * n, t.schema.field(by).type), pa.array(r.states, pa.int64()), pa.array(r.pi), pa.array([r.ledger.iterations] * n, pa.int64()), pa.array([r.residual] * n)], names=[by, "state", "pi", "iterations", "residual"])

    return edges.select(by, "src", "dst", "prob").groupBy(by).applyInArrow(one, f"{by} {kind}, state long, pi double, iterations long, residual double")


LOG_SCHEMA = "chain string, method string, width int, depth int, iteration long, passes long, matvecs long, residual double, ritz_re double, ritz_im double, rank int, seconds double"


def sweep(edges: DataFrame, grid: list[dict], name: str = "chain", **options) -> DataFrame:
    """The convergence logs of many settings on one chain, each setting a task of its own: edges are sent once a setting.

    grid: keyword arguments of ``solve_arrays``, a driver-side list; a chain of more than ``TASK_EDGES`` edges raises.
    """
    runs = F.explode(F.sequence(F.lit(0), F.lit(len(grid) - 1))).alias("run")
    sent = edges.select(runs, "src", "dst", "prob")

    def one(t: pa.Table) -> pa.Table:
        src, dst, prob = task_edges(t)
        r = solve_arrays(src, dst, prob, chain=name, **(options | grid[t.column("run")[0].as_py()]))
        names = [x.split()[0] for x in LOG_SCHEMA.split(", ")]
        types = {"string": pa.string(), "int": pa.int32(), "long": pa.int64(), "double": pa.float64()}
        return pa.table([pa.array([row[c] for row in r.log], types[k]) for c, k in (x.split() for x in LOG_SCHEMA.split(", "))], names=names)

    return sent.groupBy("run").applyInArrow(one, LOG_SCHEMA)


def check_vectors(edges: DataFrame, **options) -> LocalResult:
    """A small chain solved on the driver (tests, diagnostics)."""
    t = edges.select("src", "dst", "prob").toArrow()
    return solve_arrays(*(t.column(c).to_numpy() for c in ("src", "dst", "prob")), **options)
