"""Successions of more states than a driver should hold: states are dealt into ranges by a hash, and a range's task has its edges, its states and its part of every vector.

A pass is one stage: a range adds up what it was sent, and sends each other range sums over its own edges, in an order both know since the ranges were made; some
passes make a job, whose last vectors are written. The driver sees a triangle or a few numbers of each range.
"""

from __future__ import annotations

import ctypes
import gc
import pickle
import time
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import RDD, StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.work import discard, written
from . import packed, smalldense
from .chain import SuccessionChain
from .cost import CostLedger
from .kernel import LocalResult, _next_check

TURN = 6  # passes of a job; their shuffles lie on the disks until it ends
BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"
ROWS = 1024  # sequences that a task gets at once
WHOLE, LOOPS = -1, -2  # senders besides ranges: a range's own part, and what stays
HOME, OF_HOME = 32, (1 << 20) - 1  # a label is a class, a range of 20 bits, a place of 32 bits


def _give_back() -> None:
    """A Python worker lives on for other tasks, beside those of its executor: what it has freed goes back to the system."""
    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
        trim(0)


def _here(r: int) -> int:
    return r


def ranges_of(ids: np.ndarray, ranges: int) -> np.ndarray:
    mixed = np.ascontiguousarray(ids).view(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(32)
    return (mixed * np.uint64(ranges) >> np.uint64(32)).astype(np.int64)


def places_of(ids: np.ndarray, known: np.ndarray) -> np.ndarray:
    at = np.minimum(np.searchsorted(known, ids), max(0, len(known) - 1))
    if len(ids) and not (len(known) and (known[at] == ids).all()):
        raise ValueError("sequences have states that are not among the chain's")
    return at


def _cuts(sorted_ranges: np.ndarray, ranges: int) -> np.ndarray:
    return np.searchsorted(sorted_ranges, np.arange(ranges + 1))


def _least_kind(w: np.ndarray) -> np.ndarray:
    return w.astype(np.min_scalar_type(int(w.max()) if len(w) else 0))


def _sent(rows: list[tuple[int, tuple]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r for r, _ in rows], pa.int32()), pa.array([pickle.dumps(x, 5) for _, x in rows], pa.binary())], names=["r", "data"])


def _pairs(seen: np.ndarray, size: np.ndarray, ranges: int) -> Iterator[tuple[int, tuple]]:
    """Counted pairs of some sequences for the ranges of their sources: sources, how many pairs each, destinations, which of them, counts."""
    some, back = np.unique(seen, return_inverse=True)
    end = np.cumsum(size)
    after = np.r_[back[1:], 0]
    after[end - 1] = back[end - size]
    back <<= 32
    back |= after
    del seen, after
    key, w = np.unique(back, return_counts=True)
    del back
    src, dst = (key >> 32).astype(np.int32), key.astype(np.int32)
    del key
    w = _least_kind(w)
    of = ranges_of(some, ranges).astype(np.int32)[src]
    order = np.argsort(of, kind="stable").astype(np.int32)
    cut = _cuts(of[order], ranges)
    del of
    for r in range(ranges):
        at = order[cut[r] : cut[r + 1]]
        if len(at):
            s, first = src[at], np.flatnonzero(np.r_[True, src[at][1:] != src[at][:-1]])
            ends, which = np.unique(dst[at], return_inverse=True)
            yield r, ("pairs", some[s[first]], np.diff(np.r_[first, len(s)]).astype(np.int32), some[ends], which.astype(np.int32), _least_kind(w[at]))


def _laid(r: int, items: list[tuple], ranges: int) -> Iterator[tuple[int, tuple]]:
    """A range's states and its edges by destination; each range with destinations is told which, in the order in which sums will come."""
    found = [x[1:] for x in items if x[0] == "words"]
    states, visits = (np.concatenate(x) for x in zip(*found, strict=True)) if found else (np.zeros(0, np.int64), np.zeros(0, np.int64))
    order = np.argsort(states)
    states, visits = states[order], visits[order].astype(float)
    pairs = [x[1:] for x in items if x[0] == "pairs"]
    items.clear()
    known = np.unique(np.concatenate([p[2] for p in pairs])) if pairs else np.zeros(0, np.int64)
    by_range = np.argsort(ranges_of(known, ranges), kind="stable")
    rank = np.empty(len(known), np.int64)
    rank[by_range] = np.arange(len(known))
    keys, counts = [np.zeros(0, np.int64)], [np.zeros(0, np.int32)]
    while pairs:
        sources, many, ends, which, w = pairs.pop()
        keys.append(rank[np.searchsorted(known, ends)][which] << 32 | np.repeat(places_of(sources, states), many))
        counts.append(w.astype(np.int32))
    key, w = np.concatenate(keys), np.concatenate(counts)
    del keys, counts
    order = np.argsort(key)
    key, w = key[order], w[order]
    del order
    first = np.flatnonzero(np.r_[True, key[1:] != key[:-1]][: len(key)])
    key, w = key[first], np.add.reduceat(w, first, dtype=np.int64) if len(first) else w
    del first
    known = known[by_range]
    dst, src = (key >> 32).astype(np.int32), key.astype(np.int32)
    del key
    loop = known[dst] == states[src]
    at, own = src[loop], w[loop].astype(float)
    dst, src, w = dst[~loop], src[~loop], _least_kind(w[~loop])
    starts = np.flatnonzero(np.r_[True, dst[1:] != dst[:-1]][: len(dst)])
    ends = known[dst[starts]]
    cut = _cuts(ranges_of(ends, ranges), ranges)
    yield r, ("edges", {"states": states, "visits": visits, "at": at, "own": own, "starts": starts, "src": src, "w": w, "cut": cut})
    for d in range(ranges):
        if cut[d + 1] > cut[d]:
            yield d, ("into", r, ends[cut[d] : cut[d + 1]])


class Range:
    """A range in a task's memory; what stays is as in ``packed.QuickSteps``."""

    def __init__(self, r: int, held: bytes):
        self.r = r
        self.__dict__.update(pickle.loads(held))
        loop = np.zeros(len(self.states))
        loop[self.at] = self.own
        self.factor = packed.Passes()
        self.op = packed.QuickSteps(self.factor, self.states, self.visits, loop)

    def gathered(self, messages: list[tuple], least: bool) -> np.ndarray:
        out = None
        for s, y in sorted(messages, key=lambda m: m[0]):
            if out is None:
                out = np.full((len(y), len(self.states)), np.iinfo(y.dtype).max if least else 0, y.dtype)
            packed.add_sums(out, slice(None) if s == WHOLE else self.op.at if s == LOOPS else self.into[s], y, least)
        return out

    def sends(self, x: np.ndarray, j: int, least: bool) -> Iterator[tuple[int, tuple]]:
        """Messages (step, sender, a row of sums for each column) by range."""
        if len(self.src):
            y = packed.block_sums(x if least else x / self.factor.total, self.starts, self.src, self.w, least)
            for d in np.flatnonzero(np.diff(self.cut)):
                yield int(d), (j, self.r, y[:, self.cut[d] : self.cut[d + 1]])
        yield self.r, ((j, WHOLE, x) if least else (j, LOOPS, self.op.stays * x[:, self.op.at]))

    def first_labels(self) -> np.ndarray:
        """Least for a state of a range's most visited: its component is soon covered from it."""
        frequent = 63 - np.frexp(self.visits)[1].astype(np.int64)
        return (frequent << 52 | self.r << HOME | np.arange(len(self.states)))[None, :]


def _opened(part: Iterable) -> tuple[Range | None, list[tuple]]:
    held, messages = None, []
    for r, x in part:
        if isinstance(x, (bytes, bytearray)):
            held = Range(r, x)
        else:
            messages.append(x)
    return held, messages


class Ranges:
    """A succession chain laid out in ranges; vectors are tables (r, x) of pickled arrays (blocks, columns, states of the range)."""

    def __init__(self, chain: SuccessionChain):
        self.spark = spark = chain.states.sparkSession
        visits, self.n = chain.states.agg(F.sum("visits"), F.count("*")).first()
        visits, cores, block = int(visits or 0), spark.sparkContext.defaultParallelism, packed.BLOCK_EDGES
        ranges = max(1, min(cores, -(-visits // block)), -(-visits // (6 * block)))
        self.ranges = ranges = -(-ranges // cores) * cores if ranges > cores else ranges
        if ranges > OF_HOME:
            raise ValueError(f"{ranges} ranges are more than labels can name")
        most = packed.PIECE_VISITS

        def words(batches):
            for batch in batches:
                state, many = (batch.column(c).to_numpy() for c in ("state", "visits"))
                of = ranges_of(state, ranges)
                order = np.argsort(of, kind="stable")
                cut = _cuts(of[order], ranges)
                if rows := [(r, ("words", state[at], many[at])) for r in range(ranges) if len(at := order[cut[r] : cut[r + 1]])]:
                    yield _sent(rows)
            _give_back()

        def deal(batches):
            held, tokens = [], 0

            def counted():
                seen, size = (np.concatenate(x) for x in zip(*held, strict=True))
                held.clear()
                for row in _pairs(seen, size[size > 0], ranges) if len(seen) else ():
                    yield _sent([row])
                _give_back()

            for batch in batches:
                col = batch.column("ids")
                seen, size = col.flatten().to_numpy(), np.diff(col.offsets.to_numpy())
                ends, a = np.cumsum(size), 0
                while a < len(size):  # a batch may be many pieces
                    before = int(ends[a - 1]) if a else 0
                    b = min(int(np.searchsorted(ends, before + most - tokens)) + 1, len(size))
                    held.append((seen[before : ends[b - 1]], size[a:b]))
                    tokens, a = tokens + int(ends[b - 1]) - before, b
                    if tokens >= most:
                        yield from counted()
                        tokens = 0
                held[:] = [tuple(x.copy() for x in y) for y in held]  # the batch goes
                del batch, col, seen, size, ends
            if held:
                yield from counted()
            _give_back()

        def laid(part):
            of: dict[int, list] = {}
            for r, data in part:
                of.setdefault(r, []).append(pickle.loads(data))
            for r in sorted(of):
                yield from _laid(r, of.pop(r), ranges)
            _give_back()

        def joined(part):
            edges, into = {}, {}
            for r, x in part:
                if x[0] == "edges":
                    edges[r] = x[1]
                else:
                    into.setdefault(r, {})[x[1]] = x[2]
            for r, e in edges.items():
                told = {s: places_of(ids, e["states"]).astype(np.int32) for s, ids in into.pop(r, {}).items()}
                yield r, len(e["src"]), pickle.dumps(e | {"into": told}, 5)
            del edges, into
            _give_back()

        sent = chain.sequences.select("ids").mapInArrow(deal, "r int, data binary").unionByName(chain.states.select("state", "visits").mapInArrow(words, "r int, data binary"))
        most_rows = int(spark.conf.get(BATCH))
        spark.conf.set(BATCH, str(min(ROWS, most_rows) if most_rows > 0 else ROWS))
        try:
            rows = sent.rdd  # planned here
        finally:
            spark.conf.set(BATCH, str(most_rows))
        rows = self._dealt(self._dealt(rows.map(tuple)).mapPartitions(laid)).mapPartitions(joined)
        self.table = written(spark.createDataFrame(rows, "r int, edges long, held binary"), "ranges")
        del sent, rows
        self._swept()
        self.edges = int(self.table.agg(F.sum("edges")).first()[0] or 0)
        self.fixed = self._dealt(self.table.select("r", "held").rdd.map(tuple)).persist(StorageLevel.MEMORY_AND_DISK_DESER)  # lost parts are made again

    def _dealt(self, rdd: RDD) -> RDD:
        return rdd.partitionBy(self.ranges, _here)

    def _kept(self, rdd: RDD, more: str = "") -> DataFrame:
        out = written(self.spark.createDataFrame(rdd, f"r int, x binary{more}"), "vectors")
        self._swept()
        return out

    def _swept(self) -> None:
        """Shuffles that nothing reads any more leave the disks once both sides of the driver have let them go."""
        gc.collect()
        self.spark.sparkContext._jvm.System.gc()

    def close(self) -> None:
        self.fixed.unpersist()
        discard(self.table)
        del self.fixed
        self._swept()

    def each(self, f) -> DataFrame:
        """A vector made by a range alone."""

        def made(part):
            held, _ = _opened(part)
            if held is not None:
                yield held.r, pickle.dumps(f(held)[None], 5)

        return self._kept(self.fixed.mapPartitions(made))

    def mapped(self, x: DataFrame, f) -> DataFrame:
        """Of a range's blocks other ones."""
        return self._kept(x.rdd.map(lambda row: (row.r, pickle.dumps(f(pickle.loads(row.x)), 5))))

    def told(self, x: DataFrame, f) -> list:
        """A few numbers of each range."""
        return x.rdd.map(lambda row: f(pickle.loads(row.x))).collect()

    def _last(self, x: DataFrame, j) -> RDD:
        return self._dealt(x.rdd.map(lambda row: (row.r, (j, WHOLE, pickle.loads(row.x)[-1]))))

    def run(self, x: DataFrame, steps: int, keep: int = 0, least: bool = False) -> DataFrame:
        """``steps`` steps on from the last block: the last ``keep`` + 1 blocks, and how many states changed in the last step where labels move."""

        def moved(j):
            def move(part):
                held, messages = _opened(part)
                if held is not None:
                    yield from held.sends(held.gathered([m[1:] for m in messages], least), j, least)

            return move

        def taken(part):
            held, messages = _opened(part)
            if held is not None:
                of: dict[int, list] = {}
                for j, *m in messages:
                    of.setdefault(j, []).append(m)
                x = [held.gathered(of[j], least) for j in sorted(of)]
                yield held.r, pickle.dumps(np.stack(x), 5), sum(int((x[-1] != y).sum()) for s, y in of[max(of)] if s == WHOLE)

        at = self._last(x, 0)
        rounds = [at]
        for j in range(1, steps + 1):
            at = self._dealt(self.fixed.union(at).mapPartitions(moved(j)))
            rounds = [*rounds[-keep:], at] if keep else [at]
        last = self.fixed
        for at in rounds:
            last = last.union(at)
        rdd = last.mapPartitions(taken)
        del last, at, rounds
        return self._kept(rdd, ", changed long")

    def components(self) -> DataFrame:
        """Each state's least label among those that reach it: one for a component, as every state is reached back from those it reaches."""
        label, changed = self.each(Range.first_labels), 1
        while changed:
            new = self.run(label, 4, least=True)
            changed = new.agg(F.sum("changed")).first()[0]
            discard(label)
            label = new
        return label

    def balanced(self, x: DataFrame, label: DataFrame) -> DataFrame:
        """Each column scaled so that a component has its share of the visits; a label's own range adds up what all ranges have of it."""

        def ask(part):
            held, messages = _opened(part)
            if held is not None:
                of = {m[0]: m[2] for m in messages}
                names, which = np.unique(of["label"][0], return_inverse=True)
                sums = np.stack([np.bincount(which, weights=v, minlength=len(names)) for v in (held.op.total, *of["x"])])
                home = names >> HOME & OF_HOME
                for h in np.unique(home):
                    yield int(h), (held.r, names[home == h], sums[:, home == h])

        def answer(part):
            asked = [m for _, m in part]
            if asked:
                names, which = np.unique(np.concatenate([m[1] for m in asked]), return_inverse=True)
                sums = np.stack([np.bincount(which, weights=v, minlength=len(names)) for v in np.concatenate([m[2] for m in asked], axis=1)])
                factor = np.where(sums[1:] > 0, sums[:1] / np.where(sums[1:] > 0, sums[1:], 1.0), 0.0)
                for r, some, _ in asked:
                    yield r, ("factor", some, factor[:, np.searchsorted(names, some)])

        def apply(part):
            messages = list(part)
            of = {m[0]: (r, m[2]) for r, m in messages if m[0] != "factor"}
            if of:
                (r, v), (_, mine) = of["x"], of["label"]
                some, factor = (np.concatenate(y, axis=-1) for y in zip(*((m[1], m[2]) for _, m in messages if m[0] == "factor"), strict=True))
                order = np.argsort(some)
                yield r, pickle.dumps((v * factor[:, order[np.searchsorted(some[order], mine[0])]])[None], 5)

        vectors = self._last(x, "x").union(self._last(label, "label"))
        answers = self._dealt(self._dealt(self.fixed.union(vectors).mapPartitions(ask)).mapPartitions(answer))
        return self._kept(vectors.union(answers).mapPartitions(apply))

    def extract(self, window: DataFrame, how: str, rtol: float) -> smalldense.Extraction:
        def triangle(x):
            return len(x), x.shape[1], np.linalg.qr(x.reshape(-1, x.shape[2]).T, mode="r")

        found = self.told(window, triangle)
        width, m = found[0][1], (found[0][0] - 1) * found[0][1]
        r = np.linalg.qr(np.vstack([t for *_, t in found]), mode="r")
        scale = np.maximum(np.linalg.norm(r[:, :m], axis=0), 1e-300)
        return smalldense.EXTRACTIONS[how](np.hstack([r[:, :m] / scale, r[:, width:] / scale]), scale, rtol)

    def combined(self, window: DataFrame, coefficients: np.ndarray) -> DataFrame:
        return self.mapped(window, lambda x: (coefficients @ x.reshape(-1, x.shape[2])[: len(coefficients)])[None, None])

    def residual(self, v: DataFrame) -> float:
        both = self.run(v, 1, keep=1)
        off, size = np.sum(self.told(both, lambda x: (float(((x[1] - x[0]) ** 2).sum()), float((x[0] ** 2).sum()))), axis=0)
        discard(both)
        return float(np.sqrt(off / size)) if size > 0 else 1.0

    def finished(self, v: DataFrame, label: DataFrame) -> tuple[DataFrame, float]:
        """(state, pi) of the chain itself, as ``packed.solve_quick`` has it, of states with other exits; the least entry before clipping."""
        ends = self.told(v, lambda x: (float(x.sum()), float(x.min())))
        total = sum(s for s, _ in ends) or 1.0
        least = min(float(x) / total for x in (min(m for _, m in ends),))

        def turned(part):
            held, messages = _opened(part)
            if held is not None:
                yield held.r, pickle.dumps((np.clip(messages[0][2] / total, 0, None) * held.op.total / held.factor.total)[None], 5)

        raw = self._kept(self.fixed.union(self._last(v, 0)).mapPartitions(turned))
        shares = self.balanced(raw, label)
        visits = sum(self.told(shares, lambda x: float(x.sum()))) or 1.0

        def named(part):
            held, messages = _opened(part)
            if held is not None:
                free = held.op.free
                yield held.states[free].tobytes(), (messages[0][2][0, free] / visits).tobytes()

        def rows(batches):
            for batch in batches:
                for s, p in zip(batch.column("s").to_pylist(), batch.column("p").to_pylist(), strict=True):
                    yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(s, np.int64)), pa.array(np.frombuffer(p))], names=["state", "pi"])

        both = self.spark.createDataFrame(self.fixed.union(self._last(shares, 0)).mapPartitions(named), "s binary, p binary")
        out = written(both.mapInArrow(rows, "state long, pi double"), "solved")
        discard(raw, shares)
        return out, least


def solve_ranges(
    op: Ranges, width: int = 1, depth: int = 1, tol: float = 1e-10, check_every: int | str = 10, max_iter: int = 200_000, seed: int = 0, extract: str = "min_residual",
    rank_rtol: float = smalldense.RANK_RTOL, chain: str = "succession", method: str = "block", on_limit: str = "return",
) -> tuple[DataFrame, LocalResult]:
    """``kernel.solve_arrays`` with shifted images, and ``packed.solve_quick``'s start and end, on ranges: (state, pi), and all else of the result."""
    began, ledger, log = time.perf_counter(), CostLedger(), []
    label = op.components()
    raw = op.each(lambda held: np.random.default_rng([seed, held.r]).random((width, len(held.states))))
    x = op.balanced(raw, label)
    discard(raw)
    every, k, converged, found, v, res = check_every if isinstance(check_every, int) else 4, 0, False, None, None, 1.0
    while k < max_iter and not converged:
        steps = left = min(every, max_iter - k)
        while left:
            some = left if left <= depth else min(TURN, left - depth)
            new = op.run(x, some, some if left <= depth else 0)
            discard(x)
            x, left = new, left - some
        k += steps
        ledger.step(width, steps)
        t = time.perf_counter()
        found = op.extract(x, extract, rank_rtol)
        if v is not None:
            discard(v)
        v, res = op.combined(x, found.coefficients), found.residual
        ledger.extractions += 1
        if res < tol:  # verify on the vector itself
            res = op.residual(v)
            ledger.extra_pass(1)
        converged = res < tol
        ledger.extraction_seconds += time.perf_counter() - t
        log.append({"chain": chain, "method": method, "width": width, "depth": depth, "iteration": k, "passes": ledger.passes, "matvecs": ledger.matvecs_core, "residual": float(res), "ritz_re": found.ritz.real, "ritz_im": found.ritz.imag, "rank": found.rank, "seconds": time.perf_counter() - began})
        if check_every == "adaptive":
            every = _next_check(log, tol, k)
    if not converged and on_limit == "raise":
        raise RuntimeError(f"{chain}: no convergence in {k} steps, residual {res:.3g}")
    pi, least = op.finished(x if v is None else v, label)
    discard(x, label, *([] if v is None else [v]))
    ledger.seconds = time.perf_counter() - began
    none = np.zeros(0)
    return pi, LocalResult(none, none, converged, float(res), found.rank if found else 1, ledger, log, least)
