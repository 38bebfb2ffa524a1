"""The experiments: chains on the given tables, sweeps of width and depth, ablations."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .operators import builders, diagnostics, solve
from .operators import chain as chains
from .operators.chain import Chain, FactoredChain, MatrixFreeChain
from .operators.cost import saving
from .operators.kernel import sweep
from .sources import synthetic
from .sources.tables import load
from .sources.work import written

WIDTHS = [1, 2, 4, 8, 16, 32, 64, 128]
DEPTHS = [1, 4, 8, 16, 32]
HOURS = 23  # the last hour of a day


def event_types(spark: SparkSession, d: str) -> Chain:
    e = load(spark, d, "events")
    return chains.from_weights(builders.succession(e, "user_id", ["ts", "event_id"], "event_type"), "event_types")


def hour_weights(spark: SparkSession, d: str) -> DataFrame:
    e = load(spark, d, "events").select("user_id", "ts", "event_id", F.expr("timestampdiff(HOUR, timestamp_ntz'2024-01-01 00:00:00', cast(ts AS timestamp_ntz))").alias("hour"))
    return builders.succession(e, "user_id", ["ts", "event_id"], "hour")


def hour_slots(spark: SparkSession, d: str) -> Chain:
    w = hour_weights(spark, d).groupBy("src", "dst").agg(F.sum("w").alias("w"))
    return Chain(written(chains.normalise(w), "edges"), name="hour_slots")


def regional_weights(spark: SparkSession, d: str, eps: float) -> DataFrame:
    return builders.regional(*(load(spark, d, t) for t in ("lineitem", "orders", "customer", "supplier", "nation")), eps)


def regional(spark: SparkSession, d: str, eps: float = 1e-3) -> Chain:
    return Chain(written(chains.normalise(regional_weights(spark, d, eps)), "edges"), name=f"regional_{eps:g}")


def similarity_weights(spark: SparkSession, d: str, k: int = 5) -> DataFrame:
    return written(builders.knn(load(spark, d, "embeddings"), k), "knn")


def similarity(spark: SparkSession, d: str, k: int = 5) -> Chain:
    return Chain(written(chains.normalise(similarity_weights(spark, d, k)), "edges"), name="similarity")


def month_weights(spark: SparkSession, d: str) -> DataFrame:
    """Neighbouring months, weight: orders in both."""
    m = load(spark, d, "orders").groupBy(F.expr("cast(year(o_orderdate) * 12 + month(o_orderdate) as bigint)").alias("src")).agg(F.count("*").alias("n"))
    nxt = m.select((F.col("src") - 1).alias("src"), F.col("n").alias("n2"))
    up = m.join(nxt, "src").select("src", (F.col("src") + 1).alias("dst"), (F.col("n") + F.col("n2")).cast("double").alias("w"))
    return builders.undirected(up)


def month_ladder(spark: SparkSession, d: str) -> Chain:
    return chains.lazy(Chain(written(chains.normalise(month_weights(spark, d)), "edges"), name="month_ladder"))


def host_weights(spark: SparkSession, d: str) -> DataFrame:
    return builders.undirected(builders.host_links(load(spark, d, "pages")))


def hosts(spark: SparkSession, d: str) -> Chain:
    return chains.from_weights(host_weights(spark, d), "hosts")


def directed_hosts(spark: SparkSession, d: str, follow: float = 0.85) -> Chain:
    """From hosts to what their pages link to; link targets without pages of their own are dangling and spread, all restart anywhere."""
    return chains.teleport(chains.fix_dangling(chains.from_weights(builders.host_links(load(spark, d, "pages")), "directed_hosts"), "uniform"), follow)


def customer_supplier(spark: SparkSession, d: str) -> FactoredChain:
    """The lazy walk over customers (even) and suppliers (odd), an edge each way for every line between them."""
    li, o = load(spark, d, "lineitem"), load(spark, d, "orders")
    lines = li.select("l_orderkey", "l_suppkey").join(o.select(F.col("o_orderkey").alias("l_orderkey"), (F.col("o_custkey") * 2).alias("c")), "l_orderkey")
    lines = written(lines.select("c", (F.col("l_suppkey") * 2 + 1).alias("s")), "lines")
    ways = F.array(*(F.struct(F.col(x).alias("src"), F.col(y).alias("dst"), F.lit(1.0).alias("w")) for x, y in ("cs", "sc")))
    return FactoredChain((lines.select(F.inline(ways)),), 0.5, "customer_supplier")


def supplier_parts(spark: SparkSession, d: str) -> DataFrame:
    """a, b, w: suppliers, parts, their lines."""
    li = load(spark, d, "lineitem").groupBy(F.col("l_suppkey").alias("a"), F.col("l_partkey").alias("b")).agg(F.count("*").cast("double").alias("w"))
    return written(li, "supplier_parts")


def supplier_two_step(spark: SparkSession, d: str) -> FactoredChain:
    """From a supplier to a part by lines, and to a supplier of the part; the two steps are never composed."""
    ab = supplier_parts(spark, d)
    return FactoredChain((ab.select(F.col("a").alias("src"), F.col("b").alias("dst"), "w"), ab.select(F.col("b").alias("src"), F.col("a").alias("dst"), "w")), name="supplier_two_step")


def supplier_two_step_edges(spark: SparkSession, d: str) -> DataFrame:
    """src, dst, prob of the same chain, composed."""
    ab = supplier_parts(spark, d)
    return builders.two_step(ab, ab.select("b", F.col("a").alias("c"), "w")).select("src", "dst", "prob")


def roles(spark: SparkSession, d: str) -> Chain:
    return chains.from_weights(builders.succession(load(spark, d, "conversations"), "conv_id", ["turn", "role"], "role"), "roles")


def priorities(spark: SparkSession, d: str) -> Chain:
    return chains.from_weights(builders.succession(load(spark, d, "orders"), "o_custkey", ["o_orderdate", "o_orderkey"], "o_orderpriority"), "priorities")


#: Factors of the successions of order priorities: within {1, 2, 5} to another and to itself, from 3 to 4 and back, and between the two groups. 3 and 4 do not stay.
FIVE = {"other": 1.0, "same": 4.0, "swap": 9.0, "between": 6e-4}


def five_priorities(spark: SparkSession, d: str) -> Chain:
    """The five order priorities, successions within a customer both ways times ``FIVE``: two groups that hardly meet, one of which swaps its two states.

    Moduli like those of ``synthetic.FIVE_STATE``: some 0.9998 (negative) and 0.9996, then about a half.
    """
    w = builders.succession(load(spark, d, "orders"), "o_custkey", ["o_orderdate", "o_orderkey"], "o_orderpriority").groupBy("src", "dst").agg(F.sum("w").alias("w"))
    swaps = lambda c: F.left(F.col(c), F.lit(1)).isin("3", "4")
    kind = F.when(swaps("src") != swaps("dst"), FIVE["between"]).when(swaps("src"), F.when(F.col("src") == F.col("dst"), 0.0).otherwise(FIVE["swap"]))
    factor = kind.otherwise(F.when(F.col("src") == F.col("dst"), FIVE["same"]).otherwise(FIVE["other"]))
    return chains.from_weights(builders.undirected(w).withColumn("w", F.col("w") * factor), "five_priorities")


def event_sites(spark: SparkSession, d: str, channels: int) -> DataFrame:
    """state, closed, open, inact, cinact, ions: the release sites that users' events make, each once. ``channels`` successive events of a user are the
    channels, their types by name (modulo 4) what the channels are; the hour of the first is the ion number (capacity ``HOURS``)."""
    e = load(spark, d, "events").select("user_id", "ts", "event_id", "event_type")
    kinds = [r[0] for r in e.select("event_type").distinct().orderBy("event_type").collect()]  # event types: a handful
    code = F.create_map(*(F.lit(x) for i, k in enumerate(kinds) for x in (k, i % 4)))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    kind = code[F.col("event_type")]
    run = e.select(F.hour("ts").alias("ions"), F.array(*(F.lead(kind, k).over(w) if k else kind for k in range(channels))).alias("is")).where(F.col("is")[channels - 1].isNotNull())
    many = lambda k: F.size(F.filter("is", lambda x: x == k)).cast("long")
    sites = run.select(many(0).alias("closed"), many(1).alias("open"), many(2).alias("inact"), many(3).alias("cinact"), F.col("ions").cast("long").alias("ions")).distinct()
    return sites.select(synthetic.state_id(F.col("open"), F.col("inact"), F.col("cinact"), F.col("ions"), channels, HOURS).alias("state"), "*")


def json_buckets(spark: SparkSession, d: str) -> Chain:
    e = load(spark, d, "events").select("user_id", "ts", "event_id", F.get_json_object("props", "$.k").alias("k")).where("k is not null")
    return chains.from_weights(builders.succession(e, "user_id", ["ts", "event_id"], "k"), "json_props")


PART_ORDER = ["l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_shipdate"]


def parts(spark: SparkSession, d: str) -> Chain:
    w = builders.succession(load(spark, d, "lineitem"), "l_orderkey", PART_ORDER, "l_partkey").groupBy("src", "dst").agg(F.sum("w").alias("w"))
    return Chain(written(chains.normalise(w), "edges"), name="parts")


def words(spark: SparkSession, d: str) -> Chain:
    return chains.from_weights(builders.word_succession(load(spark, d, "documents")), "words")


def user_batch(spark: SparkSession, d: str) -> DataFrame:
    """chain_id, src, dst, prob: one event-type chain for each user, all with one dictionary of types."""
    e = load(spark, d, "events").select("user_id", "ts", "event_id", "event_type")
    kinds = e.select("event_type").distinct().orderBy("event_type")
    ids = {r[0]: i for i, r in enumerate(kinds.collect())}  # event types: a handful
    code = F.create_map(*(F.lit(x) for kv in ids.items() for x in kv))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    s = e.select("user_id", "ts", "event_id", code[F.col("event_type")].cast("long").alias("src"))
    s = s.select("user_id", "src", F.coalesce(F.lead("src").over(w), F.first("src").over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))).alias("dst"))
    n = s.groupBy("user_id", "src", "dst").agg(F.count("*").cast("double").alias("w"))
    return n.join(n.groupBy("user_id", "src").agg(F.sum("w").alias("t")), ["user_id", "src"]).select(F.col("user_id").alias("chain_id"), "src", "dst", (F.col("w") / F.col("t")).alias("prob"))


def trust(spark: SparkSession, d: str, follow: float = 0.85) -> Chain:
    """Document groups (language, source) joined through what they share, restarting at documents rated good and not toxic."""
    docs = load(spark, d, "documents").select("doc_id", F.concat(F.lit("l:"), F.coalesce("lang", F.lit("?"))).alias("a"), F.concat(F.lit("s:"), F.coalesce("source", F.lit("?"))).alias("b"))
    w = builders.undirected(docs.groupBy(F.col("a").alias("src"), F.col("b").alias("dst")).agg(F.count("*").cast("double").alias("w")))
    base = chains.from_weights(w, "trust")
    good = load(spark, d, "labels").where("quality = 1 and toxic = 0").select("doc_id").distinct()
    seeds = docs.join(good, "doc_id").groupBy(F.col("b").alias("label")).agg(F.count("*").alias("n"))
    total = seeds.agg(F.sum("n").alias("t"))
    pref = seeds.crossJoin(F.broadcast(total)).join(base.states, "label").select("state", (F.col("n") / F.col("t")).alias("share"))
    return chains.teleport(base, follow, written(pref, "preference"))


def seeded_similarity(spark: SparkSession, d: str, follow: float = 0.85, seeds: int = 5) -> Chain:
    """Random walk with restart at the first vectors of the similarity graph."""
    base = similarity(spark, d)
    pref = base.nodes().where(F.col("state") < seeds)
    n = max(1, pref.count())
    return chains.teleport(base, follow, pref.select("state", F.lit(1.0 / n).alias("share")))


# ---- sweeps and ablations -------------------------------------------------------------------------------------------


def width_sweep(edges: DataFrame, widths: list[int], name: str, **options) -> DataFrame:
    return sweep(edges, [{"width": w, "depth": 1} for w in widths], name, **options)


def grid_sweep(edges: DataFrame, widths: list[int], depths: list[int], name: str, **options) -> DataFrame:
    return sweep(edges, [{"width": w, "depth": t} for w in widths for t in depths], name, **options)


def release_site_sweep(spark: SparkSession, channels: int, capacity: int, rates: synthetic.Rates, name: str, widths: list[int] = WIDTHS, depths: list[int] = DEPTHS) -> DataFrame:
    """Every width alone, every depth with widths up to 16, and the method that orthonormalises after every step (``subspace``) beside them, written."""
    edges = written(synthetic.release_site(spark, channels, capacity, rates), "edges")
    grid = [{"width": w, "depth": 1} for w in widths] + [{"width": w, "depth": t} for w in widths if w <= 16 for t in depths if t > 1]
    grid += [{"width": w, "method": "subspace"} for w in widths if 1 < w <= 16]
    return written(sweep(edges, grid, name, check_every=10, seed=1, on_limit="raise"), "sweep")


def extraction_ablation(edges: DataFrame, width: int, name: str, **options) -> DataFrame:
    return sweep(edges, [{"width": width, "extract": how, "method": how} for how in ("ritz_schur", "ritz_eig", "min_residual", "gram")], name, **options)


def image_ablation(edges: DataFrame, width: int, depth: int, name: str, **options) -> DataFrame:
    return sweep(edges, [{"width": width, "depth": depth, "image": how, "method": how} for how in ("explicit", "shifted")], name, **options)


def check_ablation(edges: DataFrame, every: list[int], name: str, **options) -> DataFrame:
    """One method label for each interval."""
    return sweep(edges, [{"check_every": c, "method": f"every_{c}"} for c in every], name, **options)


def storage_ablation(spark: SparkSession, channels: int = 2, capacity: int = 20, width: int = 4, steps: int = 6) -> DataFrame:
    """storage, seconds, matvecs: the same passes over cached edges, scanned edges and regenerated edges."""
    from .operators import block
    from .operators.step import advance
    from .plans import layout

    speed = synthetic.release_site_speed(spark, channels, capacity)
    free = MatrixFreeChain(synthetic.release_site_states(spark, channels, capacity), synthetic.release_site_moves(channels, capacity, speed))
    stored = Chain(written(free.stored().edges, "edges"), name="release_site")
    cached = layout.prepare(stored)
    cached.edges.count()
    x = written(block.start(stored.nodes(), width, 1), "block")
    rows = []
    for name, c in (("cached", cached), ("scan", stored), ("matrix_free", free)):
        began = time.perf_counter()
        total = advance(c, x, steps).agg(F.sum("x0")).first()[0]
        rows.append((name, time.perf_counter() - began, steps * width, float(total)))
    cached.edges.unpersist()
    return spark.createDataFrame(rows, "storage string, seconds double, matvecs int, mass double")


def layout_ablation(spark: SparkSession, edges: DataFrame, width: int = 4, steps: int = 4) -> DataFrame:
    """layout, mass, seconds: columns evolved together or one by one."""
    from .operators import block
    from .operators.step import propagate, propagate_columns

    c = Chain(edges)
    x = written(block.start(c.nodes(), width, 1), "block")
    rows = []
    for name, move in (("rows", propagate), ("columns", propagate_columns)):
        began, y = time.perf_counter(), x
        for _ in range(steps):
            y = written(move(c, y), "block")
        rows.append((name, float(y.agg(F.sum("x0")).first()[0]), time.perf_counter() - began))
    return spark.createDataFrame(rows, "layout string, mass double, seconds double")


def compare_methods(chain: Chain, runs: list[tuple[int, int]], **options) -> list[dict]:
    """Local solves of one chain: iterations, passes, matvecs and the saving against the first run."""
    out = []
    for width, depth in runs:
        r = solve.solve(chain, width, depth, engine="local", **options)
        out.append({"width": width, "depth": depth, "converged": r.converged, **r.ledger.as_dict()})
        out[-1]["saving"] = saving(out[0]["matvecs_core"], out[-1]["matvecs_core"])
    return out


def connected(chain: Chain) -> Chain:
    """The chain on its largest component."""
    return chains.restrict(chain, written(diagnostics.largest_component(chain.edges), "largest"))
