"""Chains, plans, distributed solvers, diagnostics, surfaces."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from ergodica import workloads as W
from ergodica.functions import udfs, views
from ergodica.operators import accuracy, block, builders, convergence, diagnostics, extract, kernel, results, solve, spectrum, step
from ergodica.operators import chain as C
from ergodica.plans import layout, planner
from ergodica.sources import synthetic
from ergodica.sources import tables as T
from ergodica.sources.work import bucketed, written


@pytest.fixture(scope="module")
def coupled(spark):
    return C.Chain(synthetic.block_coupled(spark, 3, 4, 0.05), name="coupled")


def as_dict(df, k="state", v="pi"):
    return {r[k]: r[v] for r in df.collect()}


def close(a, b, tol=1e-7):
    assert a.keys() == b.keys() and max(abs(a[k] - b[k]) for k in a) < tol


def test_distributed_equals_kernel_and_truth(spark, coupled):
    truth = accuracy.dense_reference(coupled.edges)
    r = solve.block_power(coupled, 3, check_every=4, max_iter=40)
    assert r.converged and r.residual < 1e-10
    close(as_dict(r.pi), truth)
    assert r.ledger.matvecs_core == 3 * r.ledger.iterations and r.log.count() == r.ledger.extractions
    close(as_dict(solve.solve(coupled, 3, engine="local").pi), truth)
    w = solve.window_block(coupled, 2, 2, check_every=6, max_iter=40, image="explicit", extract="ritz_schur")
    close(as_dict(w.pi), truth)


def test_limit(coupled):
    with pytest.raises(RuntimeError):
        solve.power(coupled, max_iter=4, check_every=4, on_limit="raise")
    assert not solve.window_power(coupled, 2, max_iter=4, check_every=4).converged


def test_subspace_values(coupled):
    r, pairs = solve.subspace(coupled, 4, 3, tol=1e-4, max_iter=12)
    want = np.abs(spectrum.dense_spectrum(coupled.edges))[:3]
    assert np.allclose([x.magnitude for x in pairs.orderBy("rank").collect()], want, atol=1e-3)


def test_step_conserves_mass_and_layouts_agree(coupled):
    x = block.start(coupled.nodes(), 3, 5)
    y = step.propagate(coupled, x)
    assert diagnostics.mass_drift(x, y) < 1e-12
    z = step.propagate_columns(coupled, x)
    gap = y.join(z.select("state", *(F.col(c).alias(f"z_{c}") for c in block.columns(3))), "state").agg(F.max(F.abs(F.col("x2") - F.col("z_x2")))).first()[0]
    assert gap < 1e-14
    wide = step.propagate(coupled, block.start(coupled.nodes(), 40, 5))
    assert block.width_of(wide) == 40 and abs(block.mass(wide)[39] - 1) < 1e-12


def test_blocks(spark):
    nodes = spark.range(50).withColumnRenamed("id", "state")
    for kind in ("random", "indicator"):
        b = block.start(nodes, 4, 1, kind)
        assert np.allclose(block.mass(b), 1) and diagnostics.rank(b) == 4
    q = block.start_orthonormal(nodes, 3)
    r = extract.tsqr(q, block.columns(3))
    assert np.allclose(np.abs(r), np.eye(3), atol=1e-10)
    long = block.to_long(block.start(nodes, 2, 1))
    assert block.to_wide(long, 2).count() == 50


def test_tsqr_tree(spark):
    df = spark.range(400, numPartitions=40).select(F.sin("id").alias("a"), F.cos(F.col("id") * 2).alias("b"))
    full = np.linalg.qr(np.array(df.collect()), mode="r")
    assert np.allclose(np.abs(extract.tsqr(df, ["a", "b"], fan=8)), np.abs(full))


def test_diagnostics(spark):
    assert diagnostics.period(synthetic.cycle(spark, 6)) == 6
    two = synthetic.cycle(spark, 3).unionByName(synthetic.cycle(spark, 2).select(F.col("src") + 10, F.col("dst") + 10, "prob").toDF("src", "dst", "prob"))
    assert {r["count"] for r in diagnostics.components(two).groupBy("component").count().collect()} == {2, 3}
    assert diagnostics.largest_component(two).count() == 3
    bridge = two.unionByName(spark.createDataFrame([(0, 10, 0.1)], "src long, dst long, prob double"))
    assert diagnostics.strong_components(bridge).select("component").distinct().count() == 2
    assert diagnostics.check(C.Chain(synthetic.birth_death(spark, 6))) == {"strong_components": 1, "irreducible": True, "period": 1}


def test_birth_death_product_form_and_reversibility(spark):
    e = synthetic.birth_death(spark, 8)
    truth = accuracy.birth_death_pi(8, 0.3, 0.2)
    close(accuracy.dense_reference(e), dict(enumerate(truth)))
    pi = spark.createDataFrame([(i, float(p)) for i, p in enumerate(truth)], "state long, pi double")
    c = C.Chain(e)
    assert diagnostics.reversible(c, pi)
    back = {(r.src, r.dst): r.prob for r in C.reverse(c, pi).collect()}
    assert all(abs(back[(r.src, r.dst)] - r.prob) < 1e-12 for r in e.collect())
    assert convergence.residual(c, pi.withColumnRenamed("pi", "x0")) < 1e-14


def test_repairs(spark):
    e = spark.createDataFrame([(0, 1, 1.0), (1, 2, 1.0), (3, 0, 0.5), (3, 1, 0.5)], "src long, dst long, prob double")
    c = C.Chain(e)
    assert [r.state for r in C.dangling(c).collect()] == [2]
    assert C.validate(c)["dangling"] == 1
    assert C.dangling(C.fix_dangling(c)).isEmpty()
    assert C.fix_dangling(c, "drop").edges.isEmpty()
    u = C.fix_dangling(c, "uniform")
    assert abs(block.mass(step.propagate(u, block.start(u.nodes(), 1, 1)))[0] - 1) < 1e-12
    t = C.teleport(C.fix_dangling(c), 0.85)
    assert abs(block.mass(step.propagate(t, block.start(t.nodes(), 2, 1)))[1] - 1) < 1e-12


def test_empty_chain(spark):
    e = spark.createDataFrame([], "src string, dst string, w double")
    edges, states = C.encode(e)
    assert edges.isEmpty() and states.isEmpty() and C.normalise(e).isEmpty()


def test_encode_is_dense_and_ordered(spark):
    e = spark.createDataFrame([("b", "a", 1.0), ("c", None, 1.0), ("a", "c", 2.0)], "src string, dst string, w double")
    _, states = C.encode(e)
    assert [(r.state, r.label) for r in states.orderBy("state").collect()] == [(0, "a"), (1, "b"), (2, "c")]


def test_release_site(spark):
    assert synthetic.release_site_size(2, 10_968) == 109_690 and synthetic.release_site_size(40, 100) == 1_246_441
    speed = synthetic.release_site_speed(spark, 3, 5)
    rows = synthetic.release_site_states(spark, 3, 5)
    assert rows.count() == synthetic.release_site_size(3, 5)
    free = C.MatrixFreeChain(rows, synthetic.release_site_moves(3, 5, speed))
    stored = free.stored()
    v = C.validate(stored)
    assert v["off"] == 0 and v["bad"] == 0 and v["dangling"] == 0
    x = block.start(rows, 2, 1)
    a, b = step.propagate(free, x), step.propagate(stored, x)
    assert a.join(b.withColumnsRenamed({"x0": "y0", "x1": "y1"}), "state").where("abs(x0 - y0) + abs(x1 - y1) > 1e-14").isEmpty()


def test_trends_on_release_site(spark):
    e = synthetic.release_site(spark, 2, 30)
    run = lambda w, t: kernel.check_vectors(e, width=w, depth=t, check_every=10, seed=1).ledger
    base, wide, window = run(1, 1), run(16, 1), run(1, 4)
    assert wide.iterations < 0.2 * base.iterations  # fewer passes with width
    assert window.matvecs_core < 0.75 * base.matvecs_core  # and a short window nearly halves
    assert run(1, 8).matvecs_core > 0.7 * window.matvecs_core  # longer ones gain little


def test_width_pays_on_a_ladder(spark, sf2):
    """Few slow modes: matvecs fall with width, depth beyond 4 gains little."""
    e = W.month_ladder(spark, sf2).edges
    run = lambda w, t: kernel.check_vectors(e, width=w, depth=t, check_every=10, seed=1, image="explicit").ledger
    base, eight, window, longer = run(1, 1), run(8, 1), run(1, 4), run(1, 8)
    assert eight.matvecs_core < 0.4 * base.matvecs_core and window.matvecs_core < 0.2 * base.matvecs_core and longer.matvecs_core > 0.8 * window.matvecs_core


def test_gap_decides_the_width(spark, sf2):
    e = W.regional(spark, sf2, 1e-3).edges
    run = lambda w, t: kernel.check_vectors(e, width=w, depth=t, check_every=5, seed=1).ledger
    assert run(5, 1).iterations <= 15 < 1000 < run(4, 1).iterations


def test_crowded_spectrum_does_not_reward_width(spark, sf2):
    e = W.similarity(spark, sf2).edges
    run = lambda w, t: kernel.check_vectors(e, width=w, depth=t, check_every=5, seed=1).ledger
    assert run(8, 1).matvecs_core > run(1, 1).matvecs_core >= run(1, 8).matvecs_core


def test_planner_and_plans(spark, coupled):
    assert planner.choose_engine(coupled) == "local" and planner.choose_join(1000, 4) == "broadcast" and planner.choose_join(10**10, 4) == "shuffle_hash"
    assert planner.choose_width(spectrum.costs([1, 0.999, 0.998, 0.5]), 1.0, 0.01) == 3
    prepared = layout.prepare(coupled, 4)
    x = block.start(coupled.nodes(), 2, 1)
    text = layout.plan_text(step.propagate(prepared, x, "broadcast"))
    assert "BroadcastHashJoin" in text and "CartesianProduct" not in text


def test_warm_starts(coupled):
    truth = solve.solve(coupled, 2, check_every=2).pi.select("state", F.col("pi").alias("x0"))
    for engine in ("local", "distributed"):
        r = solve.solve(coupled, 2, engine=engine, check_every=2, start=truth, tol=1e-9)
        assert r.converged and r.ledger.iterations == 2


@pytest.mark.parametrize("least_hub", [10_000, 2])
def test_laid_out_edges_are_never_shuffled(spark, least_hub):
    """Three passes: one exchange each, of partial sums; hubs add an exchange of the block, not of the edges."""
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    rows = [(0, j, 1 / 40) for j in range(1, 41)] + [(j, 0, 0.5) for j in range(1, 41)] + [(j, j % 40 + 1, 0.5) for j in range(1, 41)]
    c = C.Chain(spark.createDataFrame(rows, "src long, dst long, prob double"))
    laid = layout.laid_out(c, n, least_hub)
    assert (laid.hubs is not None) == (least_hub == 2)
    x = bucketed(block.start(c.nodes(), 2, 1), ["state"], n, "block")
    y = step.advance(laid, x, 3, "shuffle_hash")
    text = layout.plan_text(y)
    edges_scan = [p for p in text.split("(") if "Scan parquet" in p and "ergodica_edges" in p and "Bucketed: true" in p]
    assert edges_scan and "CartesianProduct" not in text
    tree = text[: text.index("(1)  ") if "(1)  " in text else len(text)].splitlines()
    for i, line in enumerate(tree):
        if "ergodica_edges" in line:
            depth = line.index("Scan")
            above = next(x for x in reversed(tree[:i]) if "Join" in x)
            assert not any("Exchange" in x for x in tree[tree.index(above) : i] if x.index(x.strip(" :+-*()0123456789")[:1]) < depth and "Broadcast" not in x)
    if least_hub > 2:
        assert text.split("\n\n")[0].count("Exchange") == 3
    plain = step.advance(c, x, 3)
    assert plain.join(y.withColumnsRenamed({"x0": "y0", "x1": "y1"}), "state").where("abs(x0 - y0) + abs(x1 - y1) > 1e-14").isEmpty() and plain.count() == y.count() == 41


def test_work_is_discarded(spark, coupled, monkeypatch):
    held = []
    monkeypatch.setattr(solve, "written", lambda df, name="step": held.append(written(df, name)) or held[-1])
    r = solve.window_block(coupled, 2, 2, check_every=6, max_iter=24, tol=0.0)
    left = [h._ergodica_place[0] for h in held if "/block-" in h._ergodica_place[0]]
    fs = lambda p: spark.sparkContext._jvm.org.apache.hadoop.fs.Path(p)
    conf = spark.sparkContext._jsc.hadoopConfiguration()
    assert len(left) > 8 and not any(fs(p).getFileSystem(conf).exists(fs(p)) for p in left)
    assert abs(r.pi.agg(F.sum("pi")).first()[0] - 1) < 1e-9


def test_local_equals_distributed_with_restart_and_dangling(spark):
    """A ladder that restarts at its first state, and a chain with a state without exits and one that nothing enters."""
    ladder = C.teleport(C.Chain(synthetic.birth_death(spark, 6)), 0.5, spark.createDataFrame([(0, 1.0)], "state long, share double"))
    e = spark.createDataFrame([(0, 1, 1.0), (1, 2, 1.0), (3, 0, 0.5), (3, 1, 0.5)], "src long, dst long, prob double")
    lost = C.fix_dangling(C.Chain(e), "uniform")
    both = C.teleport(lost, 0.85, spark.createDataFrame([(3, 0.25), (1, 0.75)], "state long, share double"))
    for c in (ladder, lost, both):
        assert planner.choose_engine(c) == "local"
        a, b = as_dict(solve.solve(c, 2, check_every=5).pi), as_dict(solve.solve(c, 2, engine="distributed", check_every=10, max_iter=60, on_limit="raise").pi)
        close(a, b)
    assert as_dict(solve.solve(ladder, 2, check_every=5).pi)[0] > 0.5
    entered = C.Chain(spark.createDataFrame([(0, 1, 1.0), (1, 2, 0.5), (1, 1, 0.5), (2, 1, 1.0)], "src long, dst long, prob double"))
    got = as_dict(solve.block_power(entered, 2, check_every=10, max_iter=60, on_limit="raise").pi)
    close(got, {0: 0.0, 1: 2 / 3, 2: 1 / 3})
    with pytest.raises(Exception, match="no convergence"):
        solve.solve(C.Chain(synthetic.cycle(spark, 5)), 1, max_iter=20, on_limit="raise")


def test_passes_count_scans(coupled):
    r = solve.iterate(coupled, 3, 1, max_iter=4, check_every=4, layout="columns")
    assert r.ledger.passes >= 12 and r.ledger.matvecs_core == 12
    r = solve.iterate(coupled, 40, 1, max_iter=1, check_every=1, tol=0.0)
    assert r.ledger.passes == 2


def test_sources(spark, tmp_path, coupled):
    T.write_chain(coupled.edges, str(tmp_path / "c"), 4)
    assert T.read_chain(spark, str(tmp_path / "c")).count() == coupled.edges.count()
    assert T.read_chain(spark, str(tmp_path / "c"), [0]).count() < coupled.edges.count()
    (tmp_path / "e.csv").write_text("a,b,1.5\nb,a,x\n")
    assert T.read_edges(spark, str(tmp_path / "e.csv"), "csv").count() == 1 and T.malformed(spark, str(tmp_path / "e.csv"), "csv").count() == 1
    for fmt in ("json", "orc", "parquet"):
        coupled.edges.select("src", "dst", F.col("prob").alias("w")).write.format(fmt).save(str(tmp_path / fmt))
        assert T.read_edges(spark, str(tmp_path / fmt), fmt).count() == coupled.edges.count()
    T.write_result(coupled.edges, str(tmp_path / "r"))


def test_builders(spark):
    df = spark.createDataFrame([(1, 1, "a"), (1, 2, "b"), (1, 3, "a"), (2, 1, "c")], "k int, t int, s string")
    got = sorted((r.src, r.dst) for r in builders.succession(df, "k", ["t"], "s").collect())
    assert got == [("a", "a"), ("a", "b"), ("b", "a"), ("c", "c")]
    assert builders.succession(df, "k", ["t"], "s", cyclic=False).count() == 2
    emb = spark.createDataFrame([(i, [float(np.cos(i)), float(np.sin(i))]) for i in range(20)], "vec_id long, embedding array<double>")
    g = builders.knn(emb, 2, blocks=3)
    one = builders.knn(emb, 2, blocks=1)
    assert sorted(map(tuple, g.select("src", "dst").collect())) == sorted(map(tuple, one.select("src", "dst").collect()))


@pytest.mark.parametrize("scale", ["sf0.01", "sf0.1"])
def test_lsh_recall(spark, scale):
    from ergodica import queries

    assert queries.knn_lsh_recall(spark, f"/root/testdata/{scale}").first().recall >= 0.9


def test_lsh_with_every_bucket_is_exact(spark, monkeypatch):
    rng = np.random.default_rng(4)
    emb = spark.createDataFrame([(i, rng.normal(size=6).tolist()) for i in range(90)], "vec_id long, embedding array<double>")
    exact = builders.knn(emb, 3)
    for size in (4096, 7):
        monkeypatch.setattr(builders, "KNN_BLOCK", size)
        assert builders.knn_lsh(emb, 3, planes=3, tables=2, probes=8).select("src", "dst").exceptAll(exact.select("src", "dst")).isEmpty()
    assert builders.knn_lsh(emb.where("false"), 3).isEmpty()


def test_surfaces(spark, coupled):
    views.register(spark, coupled, accuracy.visit_share(coupled.edges.withColumnRenamed("prob", "w")), "t_")
    assert spark.sql("select count(*) from t_chain").first()[0] == coupled.edges.count()
    assert spark.sql("select predicted_steps(0.5D, 0.25D)").first()[0] == 2.0
    x = spark.sql("select array(1.0D, 2.0D) a, array(3.0D, 4.0D) b")
    r = x.select(udfs.dot("a", "b"), udfs.norm2("a"), udfs.axpy(2, F.col("a"), F.col("b")), udfs.combine("a", "b")).first()
    assert r[0] == 11 and r[2] == [5.0, 8.0] and r[3] == 11
    assert results.running_mass(spark.createDataFrame([(1, 0.5), (2, 0.3), (3, 0.2)], "state long, pi double")).where("state = 3").first().running == pytest.approx(1)
    assert results.top_states(spark.createDataFrame([(1, 0.5), (2, 0.5)], "state long, pi double"), 1).first().state == 1


def test_table_function_solves_every_chain(spark):
    udfs.register(spark)
    rows = [(7, 0, 1, 1.0), (7, 1, 0, 1.0), (9, 0, 0, 3.0), (9, 0, 1, 1.0), (9, 1, 0, 1.0), (9, 1, 1, 3.0), (None, 2, 2, 1.0)]
    spark.createDataFrame(rows, "chain_id long, src long, dst long, w double").createOrReplaceTempView("t_chains")
    got = spark.sql("SELECT chain_id, state, round(pi, 6) AS pi FROM stationary(TABLE(t_chains) PARTITION BY (chain_id), 3, 1, 1e-12D)").collect()
    assert {tuple(r) for r in got} == {(7, 0, 0.5), (7, 1, 0.5), (9, 0, 0.5), (9, 1, 0.5), (None, 2, 1.0)}
    one = spark.sql("SELECT chain_id, pi FROM stationary(TABLE(SELECT src, dst, w FROM t_chains WHERE chain_id = 9) WITH SINGLE PARTITION, 3, 1, 1e-12D)").collect()
    assert [r.chain_id for r in one] == [None, None]


def test_accuracy(spark):
    a = spark.createDataFrame([(i, 0.1 * (i + 1)) for i in range(4)], "state long, pi double")
    r = accuracy.compare(a, a, 2).first()
    assert r.l1 == 0 and r.spearman == pytest.approx(1) and r.top_overlap == 1
    assert convergence.span_distance(a, a.withColumn("pi", F.col("pi") * -3)) < 1e-12


def test_streaming(spark, sf):
    from ergodica import queries

    live = {(r.src, r.dst): r.w for r in queries.stream_succession(spark, sf).collect()}
    batch = builders.succession(T.load(spark, sf, "events"), "user_id", ["ts", "event_id"], "event_type", cyclic=False).groupBy("src", "dst").count()
    assert live == {(r.src, r.dst): r["count"] for r in batch.collect()}


@pytest.mark.parametrize("with_state", [True, False])
def test_shuffled_events_over_many_files(spark, sf, tmp_path, with_state):
    from ergodica import queries
    from ergodica.streaming import succession as S

    e = T.load(spark, sf, "events")
    e.withColumn("part", F.pmod(F.xxhash64("event_id"), F.lit(11))).repartition(11, "part").sortWithinPartitions(F.rand(3)).drop("part").write.parquet(str(tmp_path / "events.parquet"))
    assert len(list((tmp_path / "events.parquet").glob("*.parquet"))) > 4
    want = {tuple(r) for r in builders.succession(e, "user_id", ["ts", "event_id"], "event_type", cyclic=False).groupBy("src", "dst").count().collect()}
    if with_state:
        assert {tuple(r) for r in queries.stream_succession(spark, str(tmp_path)).collect()} == want
        return
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        live = S.pairs_with_processor(S.read_events(spark, str(tmp_path / "events.parquet"), e.schema), "user_id", "ts", "event_type", "3650 days", "event_id")
        q = live.writeStream.format("memory").queryName("t_shuffled").outputMode("append").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
        q.awaitTermination()
        assert {tuple(r) for r in S.succession_counts(spark.table("t_shuffled")).where("w <> 0").collect()} == want and S.dropped(q) == 0
    finally:
        spark.conf.unset("spark.sql.streaming.stateStore.providerClass")


def test_late_rows_are_counted(spark, tmp_path):
    from ergodica.streaming import succession as S

    rows = [("a", "2024-01-02 00:00:00", "x"), ("a", "2024-01-02 00:30:00", "y"), ("a", "2024-01-01 00:00:00", "z"), ("a", "2024-01-02 00:20:00", "u")]
    for r in rows:
        spark.createDataFrame([r], "k string, ts string, s string").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    pairs = S.pairs_with_state(S.read_events(spark, str(tmp_path / "in"), "k string, ts string, s string", 1), "k", "ts", "s", "2 hours")
    q = pairs.writeStream.format("memory").queryName("t_late").outputMode("append").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert S.dropped(q) == 1
    assert {tuple(r) for r in S.succession_counts(spark.table("t_late")).where("w <> 0").collect()} == {("x", "u", 1), ("u", "y", 1)}


def test_refresher_and_windows(spark, sf, tmp_path):
    from ergodica.streaming import succession as S

    e = T.load(spark, sf, "events")
    stream = S.read_events(spark, f"{sf}/events*.parquet", e.schema)
    pairs = S.pairs_with_state(S.deduplicated(stream.withColumn("ts", F.col("ts").cast("timestamp")), "event_id", "ts", "3650 days"), "user_id", "ts", "event_type", None)
    refresh = S.Refresher(str(tmp_path / "pi"))
    pairs.writeStream.foreachBatch(refresh).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start().awaitTermination()
    pi = spark.read.parquet(str(tmp_path / "pi"))
    assert abs(pi.where("epoch = 0").agg(F.sum("pi")).first()[0] - 1) < 1e-9
    once = {r.state: r.pi for r in pi.where("epoch = 0").collect()}
    again = spark.createDataFrame([("x", "y", 1), ("y", "x", 1), ("y", "y", 1)], "src string, dst string, w long")
    twice = S.Refresher(str(tmp_path / "pi"))  # another process: all it knows is in the files
    for _ in range(2):  # a replay counts nothing twice
        twice(again, 1)
        counts = spark.read.parquet(str(tmp_path / "pi-counts"))
        assert counts.where("epoch = 1 and src = 'y'").agg(F.sum("w")).first()[0] == 2
    assert set(once) | {"x", "y"} == {r.state for r in spark.read.parquet(str(tmp_path / "pi")).where("epoch = 1").collect()}
    rows = [("a", "b", "2024-01-01 01:00:00"), ("a", "b", "2024-01-01 13:00:00"), ("b", "a", "2024-01-02 01:00:00")]
    spark.createDataFrame(rows, "src string, dst string, ts string").withColumn("ts", F.col("ts").cast("timestamp")).write.parquet(str(tmp_path / "pairs"))
    live = spark.readStream.schema("src string, dst string, ts timestamp").parquet(str(tmp_path / "pairs"))
    S.windowed_chain(live, "1 day", "12 hours").writeStream.format("memory").queryName("t_days").outputMode("complete").trigger(availableNow=True).start().awaitTermination()
    assert spark.table("t_days").agg(F.sum("w")).first()[0] == 6 and spark.table("t_days").where("w = 2").count() == 1
    assert S.succession_counts(live).isStreaming


def test_stream_joins_sessions_and_processor(spark, sf, tmp_path):
    from ergodica.streaming import succession as S

    e = T.load(spark, sf, "events")
    stream = S.read_events(spark, f"{sf}/events*.parquet", e.schema).withColumn("ts", F.col("ts").cast("timestamp"))

    def run(df, name, mode="append"):
        df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start().awaitTermination()
        return spark.table(name)

    kinds = sorted(r[0] for r in e.select("event_type").distinct().collect())[:2]
    pick = lambda k: S.read_events(spark, f"{sf}/events*.parquet", e.schema).withColumn("ts", F.col("ts").cast("timestamp")).where(F.col("event_type") == k)
    got = run(S.followed_by(pick(kinds[0]), pick(kinds[1]), "user_id", "ts", "24 hours", "3650 days"), "t_follow").count()
    assert got == builders.interval_pairs(e.where(F.col("event_type") == kinds[0]), e.where(F.col("event_type") == kinds[1]), "user_id", "ts", 86_400).count()
    sessions = run(S.session_chain(stream, "user_id", "ts", "30 minutes", "1 seconds"), "t_session")
    assert 0 < sessions.agg(F.sum("events")).first()[0] <= e.count()
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        live = run(S.pairs_with_processor(stream, "user_id", "ts", "event_type", "3650 days"), "t_pairs")
        want = builders.succession(e, "user_id", ["ts", "event_id"], "event_type", cyclic=False)
        assert live.groupBy("src", "dst").count().exceptAll(want.groupBy("src", "dst").count()).isEmpty()
    finally:
        spark.conf.unset("spark.sql.streaming.stateStore.providerClass")


def test_recommend_and_components_of_workloads(spark, sf2):
    width, table = spectrum.recommend(W.regional(spark, sf2, 1e-3), 6)
    assert width == 5 and len(table) == 6
