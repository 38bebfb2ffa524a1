"""Chains of more edges than a task takes, whose vectors the driver can hold: edges lie packed in blocks of arrays, written once, and only vectors travel.

A pass sends the vectors to the blocks (one broadcast) and gets back each block's sums; all else is the method of ``kernel``, checks included.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.work import discard, written
from .chain import FactoredChain
from .kernel import LocalResult, solve_arrays, start_block

BLOCK_EDGES = 1 << 20  # of a block
PIECE_VISITS = 1 << 21  # of sequences whose pairs a task counts at once
STAY = 0.2  # the most that a state of ``QuickSteps`` stays; some, so that loops still keep a chain from being periodic
WINDOW_BYTES = 192 << 20  # of the vectors that the driver keeps between checks


def block_sums(z: np.ndarray, starts: np.ndarray, src: np.ndarray, w: np.ndarray, least: bool) -> np.ndarray:
    """A row for each column of ``z``: sums of it times the weight, or its least, over the edges from each start to the next."""
    plain = least or (w == 1).all()
    y, flow = np.empty((len(z), len(starts)), z.dtype), np.empty(len(src), z.dtype)
    for j, v in enumerate(z):
        np.take(v, src, out=flow, mode="clip")
        if not plain:
            flow *= w
        y[j] = (np.minimum if least else np.add).reduceat(flow, starts)
    return y


def add_sums(out: np.ndarray, at: np.ndarray, part: np.ndarray, least: bool) -> None:
    for j in range(len(out)):
        out[j, at] = np.minimum(out[j, at], part[j]) if least else out[j, at] + part[j]


def packed_weights(w: np.ndarray) -> bytes:
    """Whole weights in as few bytes as the largest needs; how many tells ``unpacked`` the kind."""
    if len(w) and w.min() >= 0 and (w == np.floor(w)).all():
        for kind in (np.uint8, np.uint16, np.uint32):
            if w.max() <= np.iinfo(kind).max:
                return w.astype(kind).tobytes()
    return w.astype(np.float64).tobytes()


def unpacked(row: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """starts, src, w of a block's row of Arrow scalars."""
    starts, src = np.frombuffer(row["starts"].as_buffer(), np.int64), np.frombuffer(row["src"].as_buffer(), np.int32)
    w = row["w"].as_buffer()
    return starts, src, np.frombuffer(w, {1: np.uint8, 2: np.uint16, 4: np.uint32, 8: np.float64}[w.size // max(1, len(src)) or 8])


class Passes:
    """A factor's step and its least labels, by ``_pass``; ``total`` scales the rows of its sources, ``n`` is the number of destinations."""

    total: np.ndarray
    n: int

    def step(self, x: np.ndarray) -> np.ndarray:
        z = np.empty((x.shape[1], len(x)))
        for j in range(len(z)):
            np.divide(x[:, j], self.total, out=z[j])
        return self._pass(z, np.zeros((len(z), self.n)), False).T

    def least(self, labels: np.ndarray) -> np.ndarray:
        return self._pass(labels[None, :], np.full((1, self.n), np.iinfo(labels.dtype).max, labels.dtype), True)[0]


class Factor(Passes):
    """Weights (src, dst, w), each row of ``src`` scaled to 1 at each use, between numbered states ``src_ids`` and ``dst_ids`` (rising)."""

    def __init__(self, weights: DataFrame, src_ids: np.ndarray, total: np.ndarray, dst_ids: np.ndarray, edges: int):
        self.spark, self.n, self.total = weights.sparkSession, len(dst_ids), total
        ids = self.spark.sparkContext.broadcast((src_ids, dst_ids))

        def pack(batches):
            held, rows, block = [], 0, TaskContext.get().partitionId() << 20

            def one() -> pa.RecordBatch:
                t = pa.Table.from_batches(held)
                at = []
                for known, c in zip(ids.value, ("src", "dst"), strict=True):
                    raw = t.column(c).to_numpy()
                    k = np.minimum(np.searchsorted(known, raw), max(0, len(known) - 1))
                    if not (known[k] == raw).all():
                        raise ValueError(f"states without exits among {c}")
                    at.append(k.astype(np.int32))
                w = t.column("w").to_numpy()
                order = np.argsort(at[1], kind="stable")
                src, dst, w = at[0][order], at[1][order], w[order]
                starts = np.flatnonzero(np.r_[True, dst[1:] != dst[:-1]]).astype(np.int64)
                cols = [dst[starts].tobytes(), starts.tobytes(), src.tobytes(), packed_weights(w)]
                return pa.RecordBatch.from_arrays([pa.array([block]), *(pa.array([c], pa.binary()) for c in cols)], names=["block", "dst", "starts", "src", "w"])

            for batch in batches:
                for a in range(0, batch.num_rows, BLOCK_EDGES):
                    held.append(batch.slice(a, BLOCK_EDGES))
                    rows += held[-1].num_rows
                    if rows >= BLOCK_EDGES:
                        yield one()
                        held, rows, block = [], 0, block + 1
            if rows:
                yield one()

        dealt = weights.select("src", "dst", "w").repartition(max(1, -(-edges // BLOCK_EDGES)), "dst")
        self.blocks = written(dealt.mapInArrow(pack, "block long, dst binary, starts binary, src binary, w binary"), "packed")
        ids.destroy()
        self._learn(self.blocks.select("block", "dst").toArrow())

    def _learn(self, t: pa.Table) -> None:
        self.into = {b: np.frombuffer(d.as_buffer(), np.int32) for b, d in zip(t.column("block").to_pylist(), t.column("dst"), strict=True)}

    def _pass(self, z: np.ndarray, out: np.ndarray, least: bool) -> np.ndarray:
        """Sums over each destination's edges of ``z`` times the weight, or the least of ``z``; the columns of ``z`` are contiguous."""
        sent = self.spark.sparkContext.broadcast(z)
        kind, width, names = z.dtype, len(z), ("starts", "src", "w")

        def move(batches):
            for batch in batches:
                for r in range(batch.num_rows):
                    y = block_sums(sent.value, *unpacked({c: batch.column(c)[r] for c in names}), least)
                    yield pa.RecordBatch.from_arrays([batch.column("block").slice(r, 1), pa.array([y.tobytes()], pa.binary())], names=["block", "y"])

        t = self.blocks.select("block", "starts", "src", "w").mapInArrow(move, "block long, y binary").toArrow()
        for b, y in zip(t.column("block").to_pylist(), t.column("y"), strict=True):
            add_sums(out, self.into[b], np.frombuffer(y.as_buffer(), kind).reshape(width, -1), least)
        sent.destroy()
        return out


class Steps:
    """``kernel.Operator`` through factors; ``stay`` of the mass remains."""

    factors: list
    stay: float = 0.0
    n: int

    def step(self, x: np.ndarray) -> np.ndarray:
        y = x
        for f in self.factors:
            y = f.step(y)
        if self.stay:
            y *= 1 - self.stay
            for j in range(x.shape[1]):
                y[:, j] += self.stay * x[:, j]
        return y

    def run(self, x: np.ndarray, steps: int) -> np.ndarray:
        for _ in range(steps):
            x = self.step(x)
        return x

    def components(self) -> np.ndarray:
        """The least state of each state's component, where every state is reached back from those it reaches: least labels along the edges, then of labels themselves."""
        label = np.arange(self.n, dtype=np.int32)
        while True:
            seen = label
            for f in self.factors:
                seen = f.least(seen)
            new = np.minimum(label, seen)
            np.minimum.at(new, label, seen)  # a component's first state learns what its others have seen
            while (new != new[new]).any():
                new = new[new]
            if (new == label).all():
                return label
            label = new


class PackedOperator(Steps):
    """Steps on packed blocks."""

    def __init__(self, chain: FactoredChain):
        sums = [f.groupBy("src").agg(F.sum("w").alias("t"), F.count("*").alias("n")).orderBy("src").toArrow() for f in chain.factors]
        ids = [s.column("src").to_numpy() for s in sums]
        self.states, self.stay, self.n = ids[0], chain.stay, len(ids[0])
        self.total = sums[0].column("t").to_numpy()
        self.factors = [Factor(f, ids[k], s.column("t").to_numpy(), ids[(k + 1) % len(ids)], sum(s.column("n").to_pylist())) for k, (f, s) in enumerate(zip(chain.factors, sums, strict=True))]

    def close(self) -> None:
        discard(*(f.blocks for f in self.factors))


def fits(states: int, width: int, depth: int = 1) -> bool:
    return 8 * states * width * (depth + 1) <= WINDOW_BYTES


def _solve_shares(op: Steps, width: int, depth: int, seed: int, **options) -> tuple[LocalResult, np.ndarray]:
    x = start_block(op.n, width, seed)
    of = np.unique(op.components(), return_inverse=True)[1]
    share = np.bincount(of, weights=op.total) / op.total.sum()
    for j in range(width):
        x[:, j] *= (share / np.bincount(of, weights=x[:, j]))[of]
    none = np.zeros(0, np.int64)
    return solve_arrays(none, none, np.zeros(0), width, depth, states=op.states, start=x, op=op, **options), of


def solve_packed(op: PackedOperator, width: int = 1, depth: int = 1, seed: int = 0, **options) -> LocalResult:
    """Every column starts with a random vector that gives each component its share of the weights of the first factor. Where a chain falls apart, its
    stationary vector is thus the one of those shares; with one component nothing changes."""
    return _solve_shares(op, width, depth, seed, **options)[0]


# ---- closed successions ------------------------------------------------------------------------------------------------


class HeldFactor(Passes):
    """The edges of all ``spread.Range``s in one task's memory."""

    def __init__(self, ranges: list):
        self.states, self.visits = (np.concatenate([getattr(r, c) for r in ranges]) for c in ("states", "visits"))
        self.n, self.loop, self.blocks = len(self.states), np.zeros(len(self.states)), []
        first = dict(zip((r.r for r in ranges), np.cumsum([0, *(len(r.states) for r in ranges)]), strict=False))
        for r in ranges:
            self.loop[first[r.r] + r.at] = r.own
            dst = [first[d.r] + d.into[r.r] for d in ranges if r.r in d.into]
            if dst:
                self.blocks.append((np.concatenate(dst), r.starts, first[r.r] + r.src, r.w))

    def _pass(self, z: np.ndarray, out: np.ndarray, least: bool) -> np.ndarray:
        for dst, *block in self.blocks:
            add_sums(out, dst, block_sums(z, *block, least), least)
        return out


class QuickSteps(Steps):
    """A chain whose states stay for long is slow for no other reason. Here a state stays with ``STAY`` at most, its other exits keep their proportions, and
    ``solve_quick`` turns the stationary vector into that of the chain itself: where a visit is left with chance q in place of p, it counts q / p times. The difference
    of a vector and its image is the same for both, so a residual here bounds the one there. States without other exits have no part in it."""

    def __init__(self, factor: Passes, states: np.ndarray, visits: np.ndarray, loop: np.ndarray):
        self.free = visits > loop
        self.factors, self.states, self.n = [factor], states, len(states)
        self.total = np.where(self.free, visits, 0.0)
        self.at = np.flatnonzero(loop)  # few states follow themselves
        own, all_ = loop[self.at], visits[self.at]
        self.stays = np.where(own < all_, np.minimum(own / all_, STAY), 1.0)
        factor.total = visits.copy()
        factor.total[self.at] = np.where(own < all_, (all_ - own) / np.where(own < all_, 1 - self.stays, 1.0), 1.0)  # what leaves carries the rest

    def step(self, x: np.ndarray) -> np.ndarray:
        y = super().step(x)
        for j in range(x.shape[1]):
            y[self.at, j] += self.stays * x[self.at, j]
        return y


def solve_quick(op: QuickSteps, width: int = 1, depth: int = 1, seed: int = 0, **options) -> LocalResult:
    """``solve_packed``, turned back; each component again has its share of the visits."""
    r, of = _solve_shares(op, width, depth, seed, **options)
    pi = r.pi * op.total / op.factors[0].total  # q / p
    have = np.bincount(of, weights=pi)
    pi *= (np.bincount(of, weights=op.total) / op.total.sum() / np.where(have > 0, have, 1.0))[of]
    r.states, r.pi = op.states[op.free], pi[op.free]
    return r
