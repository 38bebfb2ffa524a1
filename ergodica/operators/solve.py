"""Distributed solvers: power, block, window, window-block and general subspace iteration on chains larger than a task.

A pass is one join and one aggregation; ``fuse`` passes share a plan, whose result is written to the shared folder to cut
the lineage (executors may be lost at any time). Between checks only the last block is kept; the last ``depth`` blocks before a
check are kept as a window; older ones are removed. The image of a window is the window one step on, so extraction needs no pass of its own.

A block within the planner's broadcast bound meets the edges where they lie. Beyond it, edges are laid out once (``plans.layout``), blocks are
tables bucketed by state, and the one shuffle of a pass is that of its partial sums.
"""

from __future__ import annotations

import json
import time
from collections.abc import Callable
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import CONVERGENCE_SCHEMA
from ..sources.work import bucketed, discard, written
from . import block as blocks
from .chain import Chain, FactoredChain, MatrixFreeChain, SuccessionChain
from .convergence import ResidualStop, residual
from .cost import CostLedger
from .extract import combine, extract_window, tsqr
from .kernel import LocalResult, _next_check, solve_arrays, start_block, task_edges
from .smalldense import image_of, truncate
from .step import CHUNK, propagate, propagate_columns, scans


@dataclass
class StationaryResult:
    pi: DataFrame  # state, label, pi
    log: DataFrame  # CONVERGENCE_SCHEMA
    ledger: CostLedger
    converged: bool
    residual: float
    rank: int
    least: float = 0.0  # of pi before clipping
    vector: DataFrame | None = None  # state, x0: of unit 2-norm


def log_frame(spark: SparkSession, rows: list[dict]) -> DataFrame:
    return spark.createDataFrame([tuple(r[f.name] for f in CONVERGENCE_SCHEMA.fields) for r in rows], CONVERGENCE_SCHEMA)


def finish(chain: Chain | MatrixFreeChain, v: DataFrame) -> tuple[DataFrame, float]:
    """A unit vector of any sign to probabilities; (pi with labels, least entry before clipping)."""
    total, = v.agg(F.sum("x0")).first()
    scaled = v.select("state", (F.col("x0") / F.lit(float(total or 1.0))).alias("pi"))
    least, = scaled.agg(F.min("pi")).first()
    clipped = scaled.select("state", F.greatest("pi", F.lit(0.0)).alias("pi"))
    if least is not None and least < 0:
        again, = clipped.agg(F.sum("pi")).first()
        clipped = clipped.select("state", (F.col("pi") / F.lit(float(again))).alias("pi"))
    full = chain.nodes().join(clipped, "state", "left").select("state", F.coalesce("pi", F.lit(0.0)).alias("pi"))  # states that nothing enters
    pi = chain.labelled(full) if isinstance(chain, Chain) else full.select("state", F.col("state").cast("string").alias("label"), "pi")
    return pi, float(least or 0.0)


def _ready(chain: Chain | MatrixFreeChain, width: int, join: str | None) -> tuple[Chain | MatrixFreeChain, str, Callable[[DataFrame], DataFrame]]:
    """(the chain with its states counted and, if its blocks are too large to broadcast, its edges laid out; the join; how blocks are kept)."""
    from ..plans import layout, planner

    if isinstance(chain, Chain):
        states = chain.states if chain.states is not None else written(chain.nodes().select("state", F.col("state").cast("string").alias("label")), "nodes")
        chain = replace(chain, states=states, size=states.count())
    join = join or planner.choose_join(chain.size if isinstance(chain, Chain) else chain.rows.count(), min(width, CHUNK))
    if join == "broadcast" or isinstance(chain, MatrixFreeChain):
        return chain, join, lambda b: written(b, "block")
    n = int(chain.edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return (chain if chain.hubs is not None else layout.laid_out(chain)), join, lambda b: bucketed(b, ["state"], n, "block")


def iterate(
    chain: Chain | MatrixFreeChain, width: int = 1, depth: int = 1, tol: float = 1e-10, check_every: int | str = 10, max_iter: int = 1000, seed: int = 0,
    start: str | DataFrame = "random", extract: str = "min_residual", image: str | None = None, rank_rtol: float = 1e-13, fuse: int = 5, layout: str = "rows",
    join: str | None = None, method: str = "block", on_limit: str = "return",
) -> StationaryResult:
    """The loop all distributed methods share. ``join`` None: the planner's choice by the counted size of a block."""
    began, ledger, rows = time.perf_counter(), CostLedger(), []
    image = image_of(extract, image)
    chain, join, keep = _ready(chain, width, join)
    nodes = chain.nodes()
    spark = nodes.sparkSession
    x = keep(blocks.start(nodes, width, seed, start) if isinstance(start, str) else blocks.warm_start(nodes, width, seed, start))
    move = propagate_columns if layout == "columns" else lambda c, b: propagate(c, b, join)
    every, k, converged, stop = check_every if isinstance(check_every, int) else 4, 0, False, ResidualStop(tol)
    found, vector, res, ring = None, x, 1.0, [x]
    while k < max_iter:
        discard(*ring[:-1])
        steps = min(every, max_iter - k)
        ring = [x]
        left = steps
        while left > depth:  # nothing before the last ``depth`` steps is kept
            some = min(fuse, left - depth)
            for _ in range(some):
                x = move(chain, x)
            x = keep(x)
            discard(*ring)
            ring, left = [x], left - some
        for _ in range(left):
            x = keep(move(chain, x))
            discard(*ring[: len(ring) - depth])
            ring = [*ring[-depth:], x]
        k += steps
        ledger.step(width, steps, scans(width, layout))
        t = time.perf_counter()
        if image == "explicit":
            wide, names = _window(ring[-depth:])
            cols = blocks.columns(len(names))
            norms = wide.agg(*(F.sqrt(F.sum(F.col(c) * F.col(c))).alias(c) for c in cols)).first()
            scale = np.array([max(float(norms[c] or 0.0), 1e-300) for c in cols])
            unit = combine(wide, np.diag(1 / scale), cols)
            c, kept = truncate(tsqr(unit, cols), rank_rtol)
            q = keep(combine(unit, c, cols))  # orthonormal: its image keeps the digits
            moved = keep(propagate(chain, q, join, probabilities=False))
            ledger.extra_pass(kept, scans(kept))
            found, vector = extract_window([q], extract, moved, rank_rtol)
            vector = written(vector, "vector")
            discard(q, moved)
        else:
            found, vector = extract_window(ring, extract, None, rank_rtol)
        ledger.extractions += 1
        res = found.residual
        if stop(res):
            vector = written(vector, "vector")
            res = residual(chain, vector)
            ledger.extra_pass(1)
        ledger.extraction_seconds += time.perf_counter() - t
        rows.append({"chain": chain.name, "method": method, "width": width, "depth": depth, "iteration": k, "passes": ledger.passes, "matvecs": ledger.matvecs_core, "residual": float(res), "ritz_re": found.ritz.real, "ritz_im": found.ritz.imag, "rank": found.rank, "seconds": time.perf_counter() - began})
        if stop(res):
            converged = True
            break
        if check_every == "adaptive":
            every = _next_check(rows, tol, k)
    if not converged and on_limit == "raise":
        raise RuntimeError(f"no convergence in {max_iter} steps: residual {res:.3g}")
    vector = written(vector, "vector")
    discard(*ring)
    pi, least = finish(chain, vector)
    ledger.seconds = time.perf_counter() - began
    return StationaryResult(pi, log_frame(spark, rows), ledger, converged, float(res), found.rank if found else 1, least, vector)


def _window(parts: list[DataFrame]) -> tuple[DataFrame, list[str]]:
    """Blocks side by side as one block x0 .. ."""
    from .extract import side_by_side

    wide, names = side_by_side(parts)
    every = [c for n in names for c in n]
    return wide.select("state", *(F.col(c).alias(f"x{i}") for i, c in enumerate(every))), every


def power(chain, start="random", tol: float = 1e-10, check_every: int | str = 10, max_iter: int = 1000, **options) -> StationaryResult:
    return iterate(chain, 1, 1, tol, check_every, max_iter, start=start, method="power", **options)


def block_power(chain, width: int, **options) -> StationaryResult:
    return iterate(chain, width, 1, method="block", **options)


def window_power(chain, depth: int, **options) -> StationaryResult:
    return iterate(chain, 1, depth, method="window", **options)


def window_block(chain, width: int, depth: int, **options) -> StationaryResult:
    return iterate(chain, width, depth, method="window_block", **options)


def subspace(chain: Chain | MatrixFreeChain, width: int, eigenpairs: int | None = None, tol: float = 1e-8, max_iter: int = 200, seed: int = 0, **_) -> tuple[StationaryResult, DataFrame]:
    """General subspace iteration: orthonormal columns after every step, Ritz values and vectors of the ``eigenpairs`` leading ones.

    One round to the driver for each step; the price that knowing the dominant eigenvalue removes.
    """
    began, ledger, rows = time.perf_counter(), CostLedger(), []
    want = eigenpairs or width
    chain, join, keep = _ready(chain, width, None)
    nodes = chain.nodes()
    x, z = keep(blocks.start_orthonormal(nodes, width, seed)), None
    cols = blocks.columns(width)
    values, vectors, res, converged = np.ones(1), np.eye(width), np.ones(want), False
    for k in range(1, max_iter + 1):
        old, z = z, keep(propagate(chain, x, join, probabilities=False))
        if old is not None:
            discard(old)
        ledger.step(width, 1, scans(width))
        joined, names = _pair(x, z)
        r = tsqr(joined, names[0] + names[1])
        r = np.vstack([r, np.zeros((max(0, 2 * width - r.shape[0]), 2 * width))])
        q, image = r[:, :width], r[:, width:]
        values, vectors = np.linalg.eig(q.T @ image)
        order = np.lexsort((np.abs(values - 1), -np.abs(values)))
        values, vectors = values[order], vectors[:, order]
        res = np.linalg.norm(image @ vectors - q @ vectors * values, axis=0)[:want]
        ledger.extractions += 1
        rows.append({"chain": chain.name, "method": "subspace", "width": width, "depth": 1, "iteration": k, "passes": ledger.passes, "matvecs": ledger.matvecs_core, "residual": float(res[0]), "ritz_re": float(values[0].real), "ritz_im": float(values[0].imag), "rank": width, "seconds": time.perf_counter() - began})
        if res.max() < tol:
            converged = True
            break
        rz = tsqr(z, cols)
        x = combine(z, np.linalg.pinv(rz), cols)
        if np.linalg.cond(rz) > 1e6:  # a second round restores orthogonality
            x = written(x, "block")
            x = combine(x, np.linalg.pinv(tsqr(x, cols)), cols)
        x = keep(x)
    y = np.real(vectors[:, 0] * np.conj(vectors[np.argmax(np.abs(vectors[:, 0])), 0]))
    vector = combine(x, (y / np.linalg.norm(y))[:, None], cols, ["x0"])
    pi, least = finish(chain, vector)
    spark = nodes.sparkSession
    pairs = spark.createDataFrame([(i + 1, float(np.real(v)), float(np.imag(v)), float(abs(v)), float(e)) for i, (v, e) in enumerate(zip(values[:want], res, strict=True))], "rank int, re double, im double, magnitude double, residual double")
    return StationaryResult(pi, log_frame(spark, rows), ledger, converged, float(res[0]), width, least, vector), pairs


def _pair(x: DataFrame, z: DataFrame) -> tuple[DataFrame, list[list[str]]]:
    from .extract import side_by_side

    return side_by_side([x, z])


def solve_local(chain: Chain, **options) -> StationaryResult:
    """A chain within the planner's local budget, solved in numpy by one task; restarts, preferences, dangling states and a first column to start
    from (``start``: state, x0) go with it."""
    null = lambda kind: F.lit(None).cast(kind)
    sent = chain.edges.select(F.lit(0).alias("kind"), "src", "dst", "prob").unionByName(chain.nodes().select(F.lit(1).alias("kind"), F.col("state").alias("src"), null("long").alias("dst"), null("double").alias("prob")))
    if chain.preference is not None:
        sent = sent.unionByName(chain.preference.select(F.lit(2).alias("kind"), F.col("state").alias("src"), null("long").alias("dst"), F.col("share").cast("double").alias("prob")))
    if chain.dangling is not None:
        sent = sent.unionByName(chain.dangling.select(F.lit(3).alias("kind"), F.col("state").alias("src"), null("long").alias("dst"), null("double").alias("prob")))
    warm = options.pop("start") if isinstance(options.get("start"), DataFrame) else None
    if warm is not None:
        sent = sent.unionByName(warm.select(F.lit(4).alias("kind"), F.col("state").alias("src"), null("long").alias("dst"), F.col("x0").alias("prob")))
    follow, name, given, lost, begins = chain.follow, chain.name, chain.preference is not None, chain.dangling is not None, warm is not None

    def one(t: pa.Table) -> pa.Table:
        kind = t.column("kind").to_numpy()
        of = lambda k: t.filter(pa.array(kind == k))
        states = np.unique(of(1).column("src").to_numpy())
        preference = dangling = None
        if given:
            preference = np.zeros(len(states))
            np.add.at(preference, np.searchsorted(states, of(2).column("src").to_numpy()), of(2).column("prob").to_numpy())
        if lost:
            dangling = np.isin(states, of(3).column("src").to_numpy())
        begin = {}
        if begins:
            first = np.zeros(len(states))
            np.add.at(first, np.searchsorted(states, of(4).column("src").to_numpy()), of(4).column("prob").to_numpy())
            begin["start"] = start_block(len(states), options.get("width", 1), options.get("seed", 0))
            if first.sum() > 0:
                begin["start"][:, 0] = first / first.sum()
        r = solve_arrays(*task_edges(of(0)), states=states, follow=follow, chain=name, preference=preference, dangling=dangling, **begin, **options)
        return _told(r)

    return _heard(chain, sent.withColumn("task", F.lit(0)).groupBy("task").applyInArrow(one, "state long, pi double, told string"))


def _told(r: LocalResult) -> pa.Table:
    """A task's result: a row that tells of the solve, then its states."""
    told = json.dumps({"log": r.log, "ledger": r.ledger.as_dict(), "converged": r.converged, "residual": r.residual, "rank": r.rank, "least": r.least}, default=float)
    return pa.table([pa.array([None, *r.states.tolist()], pa.int64()), pa.array([None, *r.pi.tolist()], pa.float64()), pa.array([told] + [None] * len(r.states), pa.string())], names=["state", "pi", "told"])


def _heard(chain: Chain | SuccessionChain, rows: DataFrame) -> StationaryResult:
    solved = written(rows, "solved")
    r = json.loads(solved.where("told is not null").first().told)
    pi = chain.labelled(solved.where("told is null").select("state", "pi"))
    return StationaryResult(pi, log_frame(rows.sparkSession, r["log"]), CostLedger(**r["ledger"]), r["converged"], r["residual"], r["rank"], r["least"])


def solve_factored(chain: FactoredChain, width: int, depth: int, **options) -> StationaryResult:
    """A chain of factors on packed blocks, its vectors on the driver (``packed``); the caller has seen that they fit."""
    from . import packed

    op = packed.PackedOperator(chain)
    r = packed.solve_packed(op, width, depth, chain=chain.name, **options)
    op.close()
    spark = chain.factors[0].sparkSession
    solved = spark.createDataFrame(pa.table([pa.array(r.states), pa.array(r.pi)], names=["state", "pi"]))
    pi = solved.select("state", F.col("state").cast("string").alias("label"), "pi")
    return StationaryResult(pi, log_frame(spark, r.log), r.ledger, r.converged, r.residual, r.rank, r.least)


def solve_succession(chain: SuccessionChain, width: int, depth: int, **options) -> StationaryResult:
    """Successions counted into ranges; one task solves them within the planner's local budget, else passes over the ranges (``spread``)."""
    from ..plans.planner import LOCAL_EDGES
    from . import packed, spread

    spark = chain.states.sparkSession
    ranges = spread.Ranges(chain)
    options["chain"] = chain.name
    if ranges.n == 0:
        r = _ranged(chain, spark.createDataFrame([], "state long, pi double"), LocalResult(np.zeros(0), np.zeros(0), True, 0.0, 0, CostLedger()))
    elif ranges.edges == 0 or ranges.edges <= LOCAL_EDGES:

        def one(batches):
            rows = sorted((r, held) for batch in batches for r, held in zip(*(batch.column(c).to_pylist() for c in ("r", "held")), strict=True))
            factor = packed.HeldFactor([spread.Range(*row) for row in rows])
            op = packed.QuickSteps(factor, factor.states, factor.visits, factor.loop)
            alone = LocalResult(op.states[:0], op.total[:0], True, 0.0, 0, CostLedger())  # every state follows only itself
            yield from _told(packed.solve_quick(op, width, depth, **options) if op.free.any() else alone).to_batches()

        r = _heard(chain, ranges.table.select("r", "held").coalesce(1).mapInArrow(one, "state long, pi double, told string"))
    else:
        r = _ranged(chain, *spread.solve_ranges(ranges, width, depth, **options))
    ranges.close()
    return r


def _ranged(chain: SuccessionChain, pi: DataFrame, r: LocalResult) -> StationaryResult:
    return StationaryResult(chain.labelled(pi), log_frame(pi.sparkSession, r.log), r.ledger, r.converged, r.residual, r.rank, r.least)


def solve(chain: Chain | MatrixFreeChain | FactoredChain | SuccessionChain, width: int = 8, depth: int = 1, engine: str = "auto", **options) -> StationaryResult:
    """``engine``: local (one task), distributed, or auto by the planner's count of the edges; chains of factors: packed blocks while the vectors fit;
    successions: ranges (``spread``)."""
    from ..plans.planner import choose_engine
    from .packed import fits

    if isinstance(chain, FactoredChain):
        if engine == "auto" and fits(chain.nodes().count(), width, depth):
            return solve_factored(chain, width, depth, **{k: v for k, v in options.items() if k not in ("fuse", "layout", "join")})
        chain = chain.stored()
    if isinstance(chain, SuccessionChain):
        if engine == "auto" and options.get("extract", "min_residual") == "min_residual" and image_of("min_residual", options.get("image")) == "shifted":
            return solve_succession(chain, width, depth, **{k: v for k, v in options.items() if k not in ("fuse", "layout", "join", "image")})
        chain = chain.stored()
    if engine == "auto":
        engine = choose_engine(chain)
    if engine == "local":
        keep = {k: v for k, v in options.items() if k not in ("fuse", "layout", "join")}
        return solve_local(chain.stored() if isinstance(chain, MatrixFreeChain) else chain, width=width, depth=depth, **keep)
    return iterate(chain, width, depth, **options)
