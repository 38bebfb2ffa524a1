"""The registered queries: each applies one method, builder, measure or operator to the given tables.

Numbers are rounded to six digits so that they can be compared with SQL.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import workloads as W
from .functions import udfs
from .operators import accuracy, block, builders, convergence, cost, diagnostics, kernel, results, solve, spectrum, step
from .operators import chain as C
from .plans import planner
from .sources import synthetic
from .sources.tables import load
from .sources.work import shared_dir, written
from .streaming import succession as stream

Query = Callable[[SparkSession, str], DataFrame]


def _solved(chain: C.Chain, width: int = 1, depth: int = 1, **options) -> DataFrame:
    """The engine is the planner's choice; a solve that does not converge raises."""
    return solve.solve(chain, width, depth, on_limit="raise", **options).pi


def _pi(chain: C.Chain, **options) -> DataFrame:
    return _solved(chain, **options).select("label", F.round("pi", 6).alias("pi"))


def _by_state(chain: C.Chain, **options) -> DataFrame:
    return _solved(chain, **options).select("state", F.round("pi", 6).alias("pi"))


def _claims(s, rows: list[tuple[str, bool]]) -> DataFrame:
    """claim, holds: what an experiment is to show, and whether it did."""
    return s.createDataFrame([(c, bool(h)) for c, h in rows], "claim string, holds boolean")


def _steps_of(log: DataFrame, *by: str) -> dict:
    """Of each run its last check, by the named columns (a sweep has some tens of runs)."""
    return {tuple(r[c] for c in by) if len(by) > 1 else r[by[0]]: r for r in results.last_checks(log).collect()}


def event_power(s, d):
    return _pi(W.event_types(s, d), check_every=5)


def event_block_s2(s, d):
    return _pi(W.event_types(s, d), width=2, check_every=5)


def event_window_t3(s, d):
    return _pi(W.event_types(s, d), depth=3, check_every=5)


def event_window_block(s, d):
    return _pi(W.event_types(s, d), width=2, depth=2, check_every=5)


def event_subspace(s, d):
    return _pi(W.event_types(s, d), width=3, engine="local", method="subspace", extract="ritz_schur", check_every=5)


def event_block_distributed(s, d):
    r = solve.block_power(W.event_types(s, d), 2, check_every=5, max_iter=40)
    return r.pi.select("label", F.round("pi", 6).alias("pi"))


def event_window_distributed(s, d):
    r = solve.window_block(W.event_types(s, d), 2, 2, check_every=5, max_iter=40, extract="ritz_eig")
    return r.pi.select("label", F.round("pi", 6).alias("pi"))


def hour_block_s16(s, d):
    return _by_state(W.hour_slots(s, d), width=16, check_every=10)


def hour_block_distributed(s, d):
    """Thirty fused passes between checks."""
    return _by_state(W.hour_slots(s, d), width=16, engine="distributed", check_every=30, fuse=10)


def hour_window_s4_t4(s, d):
    return _by_state(W.hour_slots(s, d), width=4, depth=4, check_every=10)


def hour_local_kernel(s, d):
    return _by_state(W.hour_slots(s, d), width=8, check_every="adaptive")


def regional_block_s5(s, d):
    return _by_state(W.regional(s, d, 0.1), width=5, check_every=5)


def regional_block_distributed(s, d):
    return _by_state(W.regional(s, d, 0.1), width=5, engine="distributed", check_every=15, fuse=15)


def regional_laid_out(s, d):
    """The same with edges bucketed by source and blocks by state, as chains beyond the broadcast bound have them."""
    return _by_state(W.regional(s, d, 0.1), width=5, engine="distributed", check_every=15, fuse=5, join="shuffle_hash")


def regional_window(s, d):
    return _by_state(W.regional(s, d, 0.1), depth=4, check_every=5, extract="ritz_eig")


def _fixed(s, chain, steps):
    nodes = chain.nodes()
    n = nodes.count()
    x = written(nodes.select("state", F.lit(1.0 / n).alias("x0")), "block")
    for _ in range(steps // 5):
        x = written(step.advance(chain, x, 5), "block")
    return x.select("state", F.round("x0", 9).alias("x"))


def event_steps_fixed(s, d):
    c = W.event_types(s, d)
    return _fixed(s, c, 5).join(c.states, "state").select("label", "x")


def regional_steps_fixed(s, d):
    return _fixed(s, W.regional(s, d, 0.1), 10)


def knn_block(s, d):
    return _by_state(W.similarity(s, d), width=4, check_every=5)


def knn_window(s, d):
    return _by_state(W.similarity(s, d), depth=8, check_every=10)


def knn_lsh_recall(s, d):
    """The exact neighbour pairs, and whether hyperplane buckets find nine in ten of them."""
    exact, near = W.similarity_weights(s, d), builders.knn_lsh(load(s, d, "embeddings"), 5)
    hit = exact.join(near.select("src", "dst", F.lit(1).alias("hit")), ["src", "dst"], "left")
    return hit.agg(F.count("*").alias("pairs"), (F.avg(F.coalesce("hit", F.lit(0))) >= 0.9).alias("enough"))


def host_rank_undirected(s, d):
    return _pi(C.lazy(W.hosts(s, d)), width=8, depth=2, check_every=20)


def host_rank_teleport(s, d):
    return _pi(C.teleport(W.hosts(s, d), 0.85), width=4, check_every=10)


def host_rank_distributed(s, d):
    """The teleporting walk solved to its end in DataFrame plans."""
    return _pi(C.teleport(W.hosts(s, d), 0.85), width=4, depth=2, engine="distributed", check_every=16, fuse=7)


def host_rank_teleport_distributed(s, d):
    """Ten teleporting passes in DataFrame plans."""
    c = C.teleport(W.hosts(s, d), 0.85)
    return _fixed(s, c, 10).join(c.states, "state").select("label", F.round("x", 6).alias("x"))


def host_rank_directed(s, d):
    """The directed walk over links: most targets have no page, so their mass is spread, and all restart."""
    return _pi(W.directed_hosts(s, d), width=2, check_every=10)


def bipartite_lazy(s, d):
    return _by_state(W.customer_supplier(s, d), width=4, check_every=10)


def supplier_two_step(s, d):
    return _by_state(W.supplier_two_step(s, d), check_every=5)


def word_chain_top100(s, d):
    """Tokens that only follow themselves are left out: they are components of their own."""
    c = builders.word_chain(load(s, d, "documents"))
    top = results.top_states(_solved(c, depth=8, check_every=60).select(F.col("label").alias("state"), F.round("pi", 9).alias("pi")), 100)
    return top.select(F.col("state").alias("label"), F.round("pi", 6).alias("pi"))


def role_chain(s, d):
    return _pi(W.roles(s, d), width=2, check_every=5)


def priority_chain(s, d):
    return _pi(W.priorities(s, d), width=2, check_every=5)


def month_ladder(s, d):
    return _by_state(W.month_ladder(s, d), width=8, depth=2, check_every=20)


def json_props_chain(s, d):
    return _pi(W.json_buckets(s, d), width=4, check_every=5)


def part_chain(s, d):
    return _by_state(W.parts(s, d), width=2, check_every=5)


def user_batch(s, d):
    r = kernel.solve_batch(W.user_batch(s, d), width=3, check_every=5)
    return r.select(F.col("chain_id").alias("user_id"), "state", F.round("pi", 6).alias("pi"))


def trust_rank(s, d):
    """Ten restarted passes towards documents rated good."""
    c = W.trust(s, d)
    return _fixed(s, c, 10).join(c.states, "state").select("label", F.round("x", 6).alias("x"))


def similarity_restart(s, d):
    return _fixed(s, W.seeded_similarity(s, d), 10).select("state", F.round("x", 6).alias("x"))


# ---- the five-state example ------------------------------------------------------------------------------------------


def five_state_pi(s, d):
    return _by_state(W.five_priorities(s, d), width=3, check_every=1)


def five_state_extractions(s, d):
    """Extractions at width 3, every step: all end within 60 steps."""
    log = results.last_checks(W.extraction_ablation(W.five_priorities(s, d).edges, 3, "five_state", check_every=1))
    return log.select("method", ((F.col("iteration") <= 60) & (F.col("residual") < 1e-8)).alias("settled"))


def five_state_eigen(s, d):
    """Sums of the powers of all eigenvalues; the traces of the chain's powers in SQL."""
    values = spectrum.dense_spectrum(W.five_priorities(s, d).edges)
    return s.createDataFrame([(k, round(float(np.sum(values**k).real), 6)) for k in range(1, 6)], "power int, total double")


def five_state_counts(s, d):
    """Steps to 1e-10 by the residual, and by the distance to the exact vector, beside what the next modulus predicts."""
    e = W.five_priorities(s, d).edges
    grid = [{"width": w, "check_every": c, "method": "residual"} for w, c in ((1, 100), (2, 100), (3, 1))] + [{"depth": t, "check_every": 1, "method": "window"} for t in (3, 4, 5)]
    truth = np.array([p for _, p in sorted(accuracy.dense_reference(e).items())])
    grid += [{"width": w, "check_every": c, "method": "distance", "truth": truth} for w, c in ((1, 100), (2, 100), (3, 1))]
    n = {k: r.iteration for k, r in _steps_of(kernel.sweep(e, grid, "five_state", seed=1, max_iter=300_000), "method", "width", "depth").items()}
    want = [convergence.predicted_iterations(float(abs(v)), 1e-10) for v in spectrum.dense_spectrum(e)[1:4]]
    return _claims(s, [
        ("residual: width 2 takes about a third of the steps of the power method, width 3 under 100", 0.6 < n["residual", 1, 1] / want[0] < 1.1 and 0.25 < n["residual", 2, 1] / n["residual", 1, 1] < 0.7 and n["residual", 3, 1] < 100),
        ("distance: within a tenth of the prediction at widths 1 and 2, under 80 steps at width 3", all(abs(n["distance", w, 1] / want[w - 1] - 1) < 0.1 for w in (1, 2)) and n["distance", 3, 1] < 80),
        ("a window of 3, 4, 5 on one column takes under 100 products, of 5 under 8", n["window", 1, 3] <= 100 and n["window", 1, 4] <= 90 and n["window", 1, 5] <= 8),
    ])


def five_state_rates(s, d):
    """The observed rate at width 3 is the fourth modulus."""
    e = W.five_priorities(s, d).edges
    fourth = float(abs(spectrum.dense_spectrum(e)[3]))
    log = W.width_sweep(e, [3], "five_state", check_every=2)
    return convergence.observed_rate(log).select("width", (F.abs(F.col("modulus") - fourth) < 0.05).alias("as_predicted"))


# ---- measures ----------------------------------------------------------------------------------------------------------


def _frequency(s, d):
    """Visit shares of event types and the open (not cyclic) succession chain."""
    e = load(s, d, "events")
    w = builders.succession(e, "user_id", ["ts", "event_id"], "event_type", cyclic=False)
    edges = C.normalise(w)
    v = accuracy.visit_share(e.select(F.col("event_type").alias("src"), F.lit(1.0).alias("w"))).select("state", F.col("pi").alias("x0"))
    return C.Chain(edges), v


def residual_of_frequency(s, d):
    return convergence.residual_table(*_frequency(s, d)).select(F.round("residual", 9).alias("residual"))


def span_distance_two_vectors(s, d):
    share = lambda t, k: load(s, d, t).groupBy(F.col(k).cast("long").alias("state")).agg(F.count("*").cast("double").alias("pi"))
    return convergence.span_distance_table(share("customer", "c_nationkey"), share("supplier", "s_nationkey")).select(F.round("distance", 9).alias("distance"))


def accuracy_measures(s, d):
    """Errors of ten passes on the hour chain against the closed form."""
    c = W.hour_slots(s, d)
    got = _fixed(s, c, 10).withColumnRenamed("x", "pi")
    e = accuracy.compare(got, accuracy.visit_share(W.hour_weights(s, d)))
    return e.select(*(F.round(c, 6).alias(c) for c in ("l1", "l2", "max_abs", "total_variation")))


def width_sweep(s, d):
    """Widths 1 to 128 on the hour chain."""
    r = _steps_of(W.width_sweep(W.hour_slots(s, d).edges, W.WIDTHS, "hour_slots", check_every=10, seed=1), "width")
    steps = [r[w].iteration for w in W.WIDTHS]
    return _claims(s, [
        ("every run converges", all(x.residual < 1e-10 for x in r.values())),
        ("steps never rise with the width", steps == sorted(steps, reverse=True)),
        ("products are steps times width", all(r[w].matvecs == w * r[w].iteration for w in W.WIDTHS)),
    ])


def grid_sweep(s, d):
    """Widths and depths on the regional chain, whose five regions leave five slow modes: the gap after the fifth decides."""
    log = written(W.grid_sweep(W.regional(s, d, 1e-3).edges, [1, 2, 4, 5, 8], W.DEPTHS, "regional", check_every=5, seed=1), "sweep")
    n = {r["width"]: r.asDict() for r in results.pivot_grid(log, "iteration").collect()}
    return _claims(s, [
        ("five columns need at most 15 steps, four over 1,000", n[5]["1"] <= 15 < 1000 < n[4]["1"]),
        ("five columns in all, by width and depth, need at most 25 steps", n[2]["4"] <= 25 and n[1]["8"] < n[1]["1"]),
        ("a deeper window never needs two checks more", all(n[w][str(b)] <= n[w][str(a)] + 10 for w in (2, 4, 5, 8) for a, b in zip(W.DEPTHS, W.DEPTHS[1:]))),
    ])


def sweep_savings(s, d):
    """The two-channel release site whose ions wander: widths 1 to 128, depths 1 to 32, the QR of every step beside them."""
    log = W.release_site_sweep(s, 2, 60, synthetic.WANDERING, "wandering")
    save = {(r.method, r.width, r.depth): r.saving for r in results.savings(log).collect()}
    steps = [_steps_of(log, "method", "width", "depth")["block", w, 1].iteration for w in W.WIDTHS]
    block = {w: save["block", w, 1] for w in W.WIDTHS}
    return _claims(s, [
        ("steps fall with every width", all(a > b for a, b in zip(steps, steps[1:]))),
        ("the best width is 8, 16 or 32 and saves over 80 per cent of the products", max(block, key=block.get) in (8, 16, 32) and max(block.values()) > 80),
        ("width 128 saves less than the best", block[128] < max(block.values()) - 10),
        ("a window of 4 on one column saves over half, 8 and 16 at most 5 per cent more", save["block", 1, 4] > 50 and max(save["block", 1, t] for t in (8, 16)) < save["block", 1, 4] + 5),
        ("a window on a block saves more than either", save["block", 4, 4] > max(block.values())),
        ("orthonormal columns at every step save no more products than the plain block", all(save["subspace", w, 1] < block[w] + 2 for w in (2, 4, 8, 16))),
    ])


def crowded_savings(s, d):
    """The six-channel release site, whose slow modes are many: no width pays, a window of 4 nearly halves the products."""
    log = W.release_site_sweep(s, 6, 20, synthetic.Rates(), "crowded")
    save = {(r.width, r.depth): r.saving for r in results.savings(log).where("method = 'block'").collect()}
    steps = [_steps_of(log, "method", "width", "depth")["block", w, 1].iteration for w in W.WIDTHS]
    return _claims(s, [
        ("steps fall with the width", all(a > b for a, b in zip(steps, steps[1:]))),
        ("no width above 1 saves products", all(save[w, 1] < 0 for w in W.WIDTHS[1:])),
        ("a window of 4 on one column saves 40 to 60 per cent", 40 < save[1, 4] < 60),
        ("depths 8 and 16 save at most 5 per cent more", max(save[1, t] for t in (8, 16)) < save[1, 4] + 5),
        ("a window saves products at widths 2 to 8 too", all(save[w, 4] > save[w, 1] + 20 for w in (2, 4, 8))),
    ])


def similarity_savings(s, d):
    """The similarity graph's crowded spectrum: width does not pay."""
    save = {(r.width, r.depth): r.saving for r in results.savings(W.grid_sweep(W.similarity(s, d).edges, [1, 4, 8], [1, 4, 8], "similarity", check_every=5, seed=1)).collect()}
    return _claims(s, [("no width saves products", max(save[4, 1], save[8, 1]) < 0), ("a window of 8 on one column does not cost any", save[1, 8] >= 0)])


def savings_cube(s, d):
    """The cube's grand total is the best saving of its finest cells."""
    cube = written(results.savings_cube(W.grid_sweep(W.regional(s, d, 1e-2).edges, [1, 5], [1, 4], "regional", check_every=5, seed=1)), "cube")
    cell, total = cube.where("level = 0").agg(F.max("best")).first()[0], cube.where("level = 7").first().best
    return _claims(s, [("the cube has 2 by 2 cells and 18 rows", cube.count() == 18 and cube.where("level = 0").count() == 4), ("its total is the best cell", abs(cell - total) < 1e-9 and total > 80)])


def extraction_ablation(s, d):
    """Extractions on the hour chain: eigen and Schur vectors keep the rate of the least residual; normal equations lose half the digits."""
    r = _steps_of(W.extraction_ablation(W.hour_slots(s, d).edges, 8, "hour_slots", check_every=10, seed=1, max_iter=2000), "method")
    least = r["min_residual"].iteration
    return _claims(s, [("eigen and Schur within two checks of the least residual", all(abs(r[m].iteration - least) <= 20 for m in ("ritz_eig", "ritz_schur"))), ("all ranks are full", all(r[m].rank == 8 for m in ("ritz_eig", "ritz_schur", "min_residual")))])


def image_ablation(s, d):
    """Explicit images cost a pass at each check, shifted ones none but the last verification."""
    r = _steps_of(W.image_ablation(W.hour_slots(s, d).edges, 4, 4, "hour_slots", check_every=10, seed=1), "method")
    return _claims(s, [
        ("both converge, explicit images in no more steps than one check above", all(x.residual < 1e-10 for x in r.values()) and r["explicit"].iteration <= r["shifted"].iteration + 10),
        ("a pass more at each check", r["explicit"].passes >= r["explicit"].iteration + r["explicit"].iteration // 10 and r["shifted"].passes <= r["shifted"].iteration + 3),
    ])


def check_ablation(s, d):
    """Extraction intervals move the stopping step by less than themselves and nothing else."""
    n = {k: r.iteration for k, r in _steps_of(W.check_ablation(W.hour_slots(s, d).edges, [1, 10, 100], "hour_slots", width=8, seed=1), "method").items()}
    return _claims(s, [(f"checks every {c}", 0 <= n[f"every_{c}"] - n["every_1"] <= c + 20) for c in (10, 100)])


def storage_ablation(s, d):
    """The same passes over cached, scanned and regenerated edges: products and mass are equal (``workloads`` has their seconds)."""
    return W.storage_ablation(s).select("storage", "matvecs", F.round("mass", 9).alias("mass"))


def layout_ablation(s, d):
    return W.layout_ablation(s, W.regional(s, d, 0.1).edges).select("layout", F.round("mass", 9).alias("mass"))


def spectrum_leading(s, d):
    """The four leading moduli by general subspace iteration, and whether a dense eigenvalue solver agrees."""
    c = W.regional(s, d, 0.1)
    found = spectrum.leading(c, 10, 4, tol=1e-8)
    exact = s.createDataFrame([(i + 1, float(abs(v))) for i, v in enumerate(spectrum.dense_spectrum(c.edges)[:4])], "rank int, modulus double")
    return found.join(exact, "rank").select("rank", (F.abs(F.col("magnitude") - F.col("modulus")) < 1e-6).alias("agrees"))


def five_state_leading(s, d):
    return spectrum.leading(C.Chain(synthetic.five_state(s)), 3, 3, tol=1e-8).select("rank", F.round("magnitude", 4).alias("magnitude"))


def spectrum_recommend(s, d):
    """Widths with their predicted cost; the fifth, after which the regions' slow modes end, is the cheapest."""
    width, table = spectrum.recommend(W.regional(s, d, 1e-3), 6)
    return s.createDataFrame([(r["width"], r["width"] == width) for r in table], "width int, recommended boolean")


def predicted_steps(s, d):
    """Steps to 1e-10 by the modulus 1 - 1/n of each supplier with n lines."""
    udfs.register(s)
    load(s, d, "lineitem").groupBy("l_suppkey").agg(F.count("*").alias("n")).where("n > 1").select("l_suppkey", ((F.col("n") - 1) / F.col("n")).alias("m")).createOrReplaceTempView("ergodica_moduli")
    return s.sql("SELECT l_suppkey, m AS modulus, round(predicted_steps(m, 1e-10D), 4) AS steps FROM ergodica_moduli")


def start_blocks(s, d):
    """Mass and rank of start blocks of either kind."""
    nodes = s.range(200).withColumnRenamed("id", "state")
    rows = []
    for kind in ("random", "indicator"):
        b = written(block.start(nodes, 4, 1, kind), "block")
        rows += [(kind, j, round(m, 9), diagnostics.rank(b)) for j, m in enumerate(block.mass(b))]
    return s.createDataFrame(rows, "kind string, column_no int, mass double, rank int")


def planner_choices(s, d):
    """The join for chains on the suppliers, parts and orders that lines name, by their counted states."""
    n = load(s, d, "lineitem").agg(*(F.countDistinct(c).alias(c) for c in ("l_suppkey", "l_partkey", "l_orderkey"))).first().asDict()
    return s.createDataFrame([(k, v, w, planner.choose_join(v, w)) for k, v in n.items() for w in (1, 16, 1024)], "chain string, states long, width int, join string")


# ---- builders and transformations --------------------------------------------------------------------------------------


def chain_edges_event(s, d):
    c = W.event_types(s, d)
    e = c.edges.join(c.states.select(F.col("state").alias("src"), F.col("label").alias("a")), "src").join(c.states.select(F.col("state").alias("dst"), F.col("label").alias("b")), "dst")
    return e.select(F.col("a").alias("src"), F.col("b").alias("dst"), F.round("prob", 6).alias("prob"))


def sliced_succession(s, d):
    """Event types, keys dealt by weeks and stitched."""
    w = builders.succession_sliced(load(s, d, "events"), "user_id", "ts", ["ts", "event_id"], "event_type", 7 * 86_400)
    return w.groupBy("src", "dst").agg(F.sum("w").cast("long").alias("w"))


def observed_pass(s, d):
    """Edges that one pass scans, as the plan itself counted them."""
    c, seen = cost.observed(W.regional(s, d, 0.1))
    step.propagate(c, block.start(c.nodes(), 2, 1)).write.format("noop").mode("overwrite").save()
    return s.createDataFrame([(int(seen.get["edges"]),)], "n_edges long")


def chain_edges_regional(s, d):
    return W.regional(s, d, 0.1).edges.select("src", "dst", F.round("prob", 6).alias("prob"))


def encoded_states(s, d):
    return W.event_types(s, d).states.select("state", "label")


def row_sums(s, d):
    return C.row_sums(W.regional(s, d, 0.01).edges).select("src", F.round("total", 6).alias("total"), "exits")


def validated(s, d):
    v = C.validate(W.regional(s, d, 0.01), 1e-9)
    return s.createDataFrame([(v["rows"], v["off"], v["bad"], v["dangling"])], "n_rows long, n_off long, n_bad long, n_dangling long")


def dangling_states(s, d):
    """Link targets without a page of their own."""
    return C.dangling(C.Chain(C.normalise(builders.host_links(load(s, d, "pages"))))).select(F.col("state").alias("label"))


def dangling_repaired(s, d):
    """States without exits before and after each repair; uniform spreading conserves mass instead."""
    targets = C.Chain(C.normalise(builders.host_links(load(s, d, "pages")).select(F.xxhash64("src").alias("src"), F.xxhash64("dst").alias("dst"), "w")))
    rows = [("none", C.dangling(targets).count())]
    for policy in ("self_loop", "drop"):
        rows.append((policy, C.dangling(C.fix_dangling(targets, policy)).count()))
    c = C.fix_dangling(targets, "uniform")
    x = written(block.start(c.nodes(), 1, 1), "block")
    rows.append(("uniform", round(abs(block.mass(step.propagate(c, x))[0] - 1), 6) > 0))
    return s.createDataFrame([(p, int(n)) for p, n in rows], "policy string, n_left int")


def lazy_edges(s, d):
    return C.lazy(W.regional(s, d, 0.1), 0.5).edges.select("src", "dst", F.round("prob", 6).alias("prob"))


def two_step_edges(s, d):
    return W.supplier_two_step_edges(s, d).select("src", "dst", F.round("prob", 6).alias("prob"))


def composed_edges(s, d):
    e = W.regional(s, d, 0.1).edges
    return C.compose(e, e).select("src", "dst", F.round("prob", 6).alias("prob"))


def reverse_chain(s, d):
    e = load(s, d, "events")
    w = builders.succession(e, "user_id", ["ts", "event_id"], "event_type")
    return C.reverse(C.Chain(C.normalise(w)), accuracy.visit_share(w)).select("src", "dst", F.round("prob", 6).alias("prob"))


def detailed_balance(s, d):
    w = builders.succession(load(s, d, "events"), "user_id", ["ts", "event_id"], "event_type")
    return C.detailed_balance(C.Chain(C.normalise(w)), accuracy.visit_share(w)).select("src", "dst", (F.round("gap", 6) + 0.0).alias("gap"))


def components(s, d):
    """Sizes of the weak components of the host graph."""
    comp = diagnostics.components(W.hosts(s, d).edges)
    return comp.groupBy("component").count().groupBy(F.col("count").alias("size")).agg(F.count("*").alias("n"))


def strong_components(s, d):
    e = W.roles(s, d).edges.unionByName(s.createDataFrame([(0, 100, 0.0), (100, 101, 1.0), (101, 100, 1.0)], "src long, dst long, prob double"))
    return diagnostics.strong_components(e).groupBy("component").agg(F.count("*").alias("size"))


def periods(s, d):
    rows = [("cycle_6", diagnostics.period(synthetic.cycle(s, 6))), ("ladder", diagnostics.period(synthetic.birth_death(s, 8))), ("hosts", diagnostics.period(W.connected(W.hosts(s, d)).edges))]
    return s.createDataFrame(rows, "chain string, period int")


def release_site_states(s, d):
    """Sizes of generated state spaces, and how many of the sites that events make (``workloads.event_sites``) are in them, and are not."""
    out = []
    for n in (1, 2, 3):
        both = synthetic.release_site_states(s, n, W.HOURS).withColumn("made", F.lit(1)).join(W.event_sites(s, d, n).withColumn("met", F.lit(1)), ["state", "closed", "open", "inact", "cinact", "ions"], "full_outer")
        out.append(both.agg(F.lit(n).alias("channels"), F.lit(W.HOURS).alias("capacity"), F.count("made").alias("n_states"), F.count_if(F.expr("made = 1 and met = 1")).alias("n_met"), F.count_if(F.expr("made is null")).alias("n_unknown")))
    return out[0].unionByName(out[1]).unionByName(out[2])


def release_site_solved(s, d):
    """Shares of each ion number where ions wander: all alike."""
    return _ion_shares(s, 2, 30, synthetic.WANDERING, width=16, check_every=20)


def release_site_full(s, d):
    """The published size of two channels, 109,690 states, solved to its end: the first ion numbers, geometric where ions are pumped out."""
    return _ion_shares(s, 2, 10_968, synthetic.PUMPED, width=1, depth=4, check_every=1000).where("ions < 8")


def _ion_shares(s, channels: int, capacity: int, rates: synthetic.Rates, **options) -> DataFrame:
    pi = _solved(C.Chain(written(synthetic.release_site(s, channels, capacity, rates), "edges"), name="release_site"), **options)
    return pi.groupBy(F.pmod("state", F.lit(capacity + 1)).alias("ions")).agg(F.round(F.sum("pi"), 6).alias("pi"))


def matrix_free_equal(s, d):
    """Transitions of the sites that events make (``workloads.event_sites``) in which the generator and the table function differ."""
    n, c = 2, W.HOURS
    speed = synthetic.release_site_speed(s, n, c)
    udfs.register(s)
    rows = written(W.event_sites(s, d, n), "sites")
    rows.createOrReplaceTempView("ergodica_sites")
    a = rows.select(F.col("state").alias("src"), F.inline(synthetic.release_site_moves(n, c, speed)))
    b = s.sql(f"SELECT t.state AS src, m.dst, m.prob FROM ergodica_sites t, LATERAL release_site_moves(CAST(closed AS INT), CAST(open AS INT), CAST(inact AS INT), CAST(cinact AS INT), CAST(ions AS INT), {n}, {c}, {speed!r}D) m")
    both = a.join(b.withColumnRenamed("prob", "q"), ["src", "dst"], "full_outer")
    return both.where("prob is null or q is null or abs(prob - q) > 1e-12").agg(F.count("*").alias("n_different"))


def release_site_source(s, d):
    """The data source's transitions out of the sites that events make (``workloads.event_sites``)."""
    from .sources import datasource

    datasource.register(s)
    df = s.read.format("release_site").option("channels", 2).option("capacity", W.HOURS).option("speed", synthetic.release_site_speed(s, 2, W.HOURS)).load()
    df = df.join(W.event_sites(s, d, 2).select(F.col("state").alias("src")), "src", "left_semi")
    return df.agg(F.countDistinct("src").alias("n_states"), F.count("*").alias("n_moves"), F.round(F.sum("prob"), 6).alias("total"))


# ---- relational surroundings -------------------------------------------------------------------------------------------


def _flow(s, d):
    w = W.regional_weights(s, d, 1.0)
    n = load(s, d, "nation").select(F.col("n_nationkey").cast("long").alias("k"), F.col("n_regionkey").cast("long").alias("r"))
    return w.join(n.select(F.col("k").alias("src"), F.col("r").alias("src_region")), "src").join(n.select(F.col("k").alias("dst"), F.col("r").alias("dst_region")), "dst")


def transition_cube(s, d):
    return _flow(s, d).cube("src_region", "dst_region").agg(F.sum("w").alias("w"), F.grouping_id().cast("long").alias("level"))


def transition_rollup(s, d):
    return _flow(s, d).rollup("src_region", "src").agg(F.sum("w").alias("w"), F.count("*").alias("n"))


def pivot_flow(s, d):
    return _flow(s, d).groupBy("src_region").pivot("dst_region", [0, 1, 2, 3, 4]).agg(F.sum("w")).select("src_region", *(F.col(f"`{i}`").alias(f"to_{i}") for i in range(5)))


def top_states(s, d):
    return results.top_states(accuracy.visit_share(W.hour_weights(s, d)), 20).select("state", F.round("pi", 6).alias("pi"))


def top_per_region(s, d):
    f = _flow(s, d).groupBy("dst_region", F.col("dst").alias("state")).agg(F.sum("w").alias("pi"))
    return results.top_per_group(f, "dst_region", 2).select("dst_region", "state", F.col("pi").alias("w"), "rank")


def running_mass(s, d):
    return results.running_mass(accuracy.visit_share(W.hour_weights(s, d))).select("state", F.round("running", 6).alias("running"))


def state_setops(s, d):
    c = load(s, d, "customer").select(F.col("c_nationkey").cast("long").alias("state"))
    p = load(s, d, "supplier").where("s_acctbal > 0").select(F.col("s_nationkey").cast("long").alias("state"))
    parts = [results.state_setop(c, p, op, every).agg(F.count("*").alias("n")).select(F.lit(f"{op}_{'all' if every else 'set'}").alias("op"), "n") for op in ("union", "intersect", "except") for every in (False, True)]
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return out


def semi_anti_states(s, d):
    o, c = load(s, d, "orders"), load(s, d, "customer")
    hit = c.join(o.select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_semi").agg(F.count("*").alias("n")).select(F.lit("entered").alias("kind"), "n")
    return hit.unionByName(c.join(o.select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_anti").agg(F.count("*").alias("n")).select(F.lit("never").alias("kind"), "n"))


def within_succession(s, d):
    w = builders.within(load(s, d, "events"), "user_id", "ts", "event_type", 6 * 3600)
    return w.groupBy("src", "dst").agg(F.sum("w").cast("long").alias("w"))


def interval_pairs(s, d):
    """Pairs of events of a user, the second of another type and at most a day later."""
    e = load(s, d, "events").select("user_id", "ts", "event_type")
    hit = builders.interval_pairs(e, e, "user_id", "ts", 86_400).where("event_type <> r_event_type")
    return hit.groupBy("user_id", "event_type").agg(F.count("*").alias("n"))


def asof_succession(s, d):
    """For each event the user's latest one of the type that follows it in the alphabet (the last: the first), at or before its time."""
    e = load(s, d, "events").select("user_id", "ts", "event_type", "event_id")
    kinds = [r[0] for r in e.select("event_type").distinct().orderBy("event_type").collect()]  # event types: a handful
    after = F.create_map(*(F.lit(x) for a, b in zip(kinds, kinds[1:] + kinds[:1], strict=True) for x in (a, b)))
    left = e.withColumn("pair", F.struct("user_id", after[F.col("event_type")].alias("kind")))
    right = e.withColumn("pair", F.struct("user_id", F.col("event_type").alias("kind")))
    return builders.as_of(left, right.select("pair", "ts", "event_id"), "pair", "ts", "event_id").select("event_id", F.col("asof").alias("last_event"))


def sql_stationary_users(s, d):
    """The table function on every user's chain, one partition of its input for each chain."""
    udfs.register(s)
    W.user_batch(s, d).select("chain_id", "src", "dst", F.col("prob").alias("w")).createOrReplaceTempView("ergodica_users")
    r = s.sql("SELECT chain_id, state, pi FROM stationary(TABLE(SELECT chain_id, src, dst, w FROM ergodica_users) PARTITION BY (chain_id), 3, 1, 1e-12D)")
    return r.select(F.col("chain_id").alias("user_id"), "state", F.round("pi", 6).alias("pi"))


def sql_stationary(s, d):
    """User 0 of ``sql_stationary_users``: its SQL asks for this user; every chain is solved."""
    return sql_stationary_users(s, d).where("user_id = 0").select("state", "pi")


def grouped_stationary(s, d):
    """The grouped aggregate on every user's chain."""
    r = W.user_batch(s, d).groupBy("chain_id").agg(udfs.stationary_of("src", "dst", "prob").alias("pi"))
    return r.select(F.col("chain_id").alias("user_id"), F.posexplode("pi").alias("at", "p")).select("user_id", "at", F.round("p", 6).alias("pi"))


def stream_succession(s, d):
    """Counts of successive event types from a file stream, run to its end."""
    path, out = f"{d}/events*.parquet", f"{shared_dir(s)}/ergodica/stream-{uuid.uuid4().hex}"
    schema = load(s, d, "events").schema
    pairs = stream.pairs_with_state(stream.read_events(s, path, schema), "user_id", "ts", "event_type", "3650 days", "event_id")
    q = pairs.writeStream.outputMode("append").option("checkpointLocation", f"{out}-state").format("parquet").option("path", f"{out}-pairs").trigger(availableNow=True).start()
    q.awaitTermination()
    if late := stream.dropped(q):
        raise ValueError(f"{late} events came later than the watermark")
    return s.read.parquet(f"{out}-pairs").groupBy("src", "dst").agg(F.sum("w").alias("w")).where("w <> 0")


def queries() -> dict[str, Query]:
    """Every public function of this module that takes (spark, sf_dir)."""
    return {k: f for k, f in globals().items() if callable(f) and getattr(f, "__module__", "") == __name__ and not k.startswith("_") and k not in ("queries", "entry")}


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The hour-slot chain by a block of eight columns."""
    return _solved(W.hour_slots(spark, sf_dir), width=8, check_every=10).select("state", "pi")
