"""Chains from ordinary tables: successions, walks, similarity graphs, damped flows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..sources.work import written
from .chain import SuccessionChain

KNN_BLOCK = 4096  # vectors of one side of a cell


def succession(df: DataFrame, key: str | list[str], order: list, state: Column | str, cyclic: bool = True) -> DataFrame:
    """(src, dst, w = 1) of each row and the next of its key; ``cyclic`` closes a key's last row to its first.

    With the closure every state is entered as often as it is left, so the stationary vector is the share of visits.
    One shuffle on the key.
    """
    keys = [key] if isinstance(key, str) else key
    w = Window.partitionBy(*keys).orderBy(*order)
    s = F.col(state) if isinstance(state, str) else state
    here = df.select(*keys, *[o for o in order if isinstance(o, str) and o not in keys], s.alias("src")) if all(isinstance(o, str) for o in order) else df.withColumn("src", s)
    nxt = F.lead("src").over(w)
    if cyclic:
        nxt = F.coalesce(nxt, F.first("src").over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)))
    return here.select("src", nxt.alias("dst")).where("src is not null and dst is not null").withColumn("w", F.lit(1.0))


def succession_sliced(df: DataFrame, key: str, ts: str, order: list[str], state: str, seconds: int, cyclic: bool = True) -> DataFrame:
    """``succession`` for keys too large for one task: a key's rows are dealt by time slices of ``seconds``, ordered within each,
    and stitched at the slices' ends by a table of one row for each key and slice."""
    at = df.select(key, *[c for c in order if c != key], F.col(state).alias("src"), F.floor(micros(ts) / (seconds * 1_000_000)).alias("slice"))
    ends = at.groupBy(key, "slice").agg(F.min_by("src", F.struct(*order)).alias("first"))
    w = Window.partitionBy(key).orderBy("slice")
    after = F.lead("first").over(w)
    if cyclic:
        after = F.coalesce(after, F.first("first").over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)))
    stitched = ends.select(key, "slice", after.alias("after"))
    inner = F.lead("src").over(Window.partitionBy(key, "slice").orderBy(*order))
    moved = at.select(key, "slice", "src", inner.alias("dst"))
    return moved.join(stitched, [key, "slice"]).select("src", F.coalesce("dst", "after").alias("dst")).where("src is not null and dst is not null").withColumn("w", F.lit(1.0))


def micros(ts: str) -> Column:
    """Microseconds of a timestamp with or without a zone."""
    return F.unix_micros(F.col(ts).cast("timestamp"))


def within(df: DataFrame, key: str, ts: str, state: str, seconds: int) -> DataFrame:
    """(src, dst, w) of each row and the *next* row of its key at most ``seconds`` later."""
    w = Window.partitionBy(key).orderBy(ts)
    gap = F.lead(micros(ts)).over(w) - micros(ts)
    return df.select(F.col(state).alias("src"), F.lead(state).over(w).alias("dst"), gap.alias("gap")).where(F.col("gap") <= seconds * 1_000_000).select("src", "dst", F.lit(1.0).alias("w"))


def interval_pairs(left: DataFrame, right: DataFrame, key: str, ts: str, seconds: int) -> DataFrame:
    """Range join by bins: every left row with the right rows of its key in (ts, ts + seconds]; an equi join on key and bin, never a nested loop.

    Columns: those of left, and of right with prefix ``r_``.
    """
    reach, size = seconds * 1_000_000, max(1, seconds) * 1_000_000
    l = left.withColumn("__t", micros(ts)).withColumn("__bin", F.explode(F.sequence(F.floor(F.col("__t") / size), F.floor((F.col("__t") + reach) / size))))  # noqa: E741
    r = right.select(*(F.col(c).alias(f"r_{c}") for c in right.columns)).withColumn("__rt", micros(f"r_{ts}")).withColumn("__rbin", F.floor(F.col("__rt") / size))
    hit = l.join(r, (F.col(key) == F.col(f"r_{key}")) & (F.col("__bin") == F.col("__rbin")))
    return hit.where((F.col("__rt") > F.col("__t")) & (F.col("__rt") <= F.col("__t") + reach)).drop("__t", "__bin", "__rt", "__rbin")


def as_of(left: DataFrame, right: DataFrame, key: str, ts: str, value: str) -> DataFrame:
    """left with ``asof``, the value of the latest right row of its key at or before its time: one sort of the union, no range join."""
    a = left.withColumns({"__side": F.lit(1), "asof": F.lit(None).cast(right.schema[value].dataType)})
    b = right.select(key, ts, F.col(value).alias("asof")).withColumn("__side", F.lit(0))
    w = Window.partitionBy(key).orderBy(ts, "__side").rowsBetween(Window.unboundedPreceding, 0)
    return a.unionByName(b, allowMissingColumns=True).withColumn("asof", F.last("asof", ignorenulls=True).over(w)).where("__side = 1").drop("__side")


def undirected(w: DataFrame) -> DataFrame:
    """Both directions, weights summed: the walk's stationary vector is the weighted degree share."""
    back = w.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w")
    return w.select("src", "dst", "w").unionByName(back).groupBy("src", "dst").agg(F.sum("w").alias("w"))


def two_step(ab: DataFrame, bc: DataFrame, block_rows: int = 400_000) -> DataFrame:
    """(a, b, w) and (b, c, w) to (src, dst, w, prob): a step through b with b's weights as probabilities; prob is w by the sum over src.

    Products never travel. Each b's two lists meet once and go, whole on the side of c, to the blocks of sources that its a-list touches; a block is a
    range of sources with some ``block_rows`` rows of ab, multiplied in numpy by a few sources at a time, so its rows leave it complete.
    """
    import numpy as np
    import pyarrow as pa

    n = -(-ab.count() // block_rows)
    cuts = np.unique(ab.approxQuantile("a", [k / n for k in range(1, n)], 1 / (4 * n))) if n > 1 else np.zeros(0)
    lists = lambda df, c, w: df.groupBy("b").agg(F.collect_list(F.struct(F.col(c).cast("long").alias("id"), F.col("w").cast("double").alias("w"))).alias(w))
    both = lists(ab, "a", "froms").join(lists(bc, "c", "tos"), "b").select(F.col("froms.id").alias("a"), F.col("froms.w").alias("wa"), F.col("tos.id").alias("c"), F.col("tos.w").alias("wc"))

    def flat(col) -> tuple[np.ndarray, np.ndarray]:
        col = col.combine_chunks() if isinstance(col, pa.ChunkedArray) else col
        return col.flatten().to_numpy(zero_copy_only=False), np.diff(col.offsets.to_numpy())

    def deal(batches):
        for batch in batches:
            if batch.num_rows == 0:
                continue
            (a, size), (w, _) = flat(batch.column("a")), flat(batch.column("wa"))
            row, block = np.repeat(np.arange(batch.num_rows), size), np.searchsorted(cuts, a, side="right")
            order = np.lexsort((block, row))
            a, w, row, block = a[order], w[order], row[order], block[order]
            first = np.flatnonzero(np.r_[True, (row[1:] != row[:-1]) | (block[1:] != block[:-1])])
            offsets, of = pa.array(np.r_[first, len(a)].astype(np.int32)), pa.array(row[first])
            yield pa.RecordBatch.from_arrays([pa.array(block[first].astype(np.int32)), pa.ListArray.from_arrays(offsets, pa.array(a)), pa.ListArray.from_arrays(offsets, pa.array(w)), batch.column("c").take(of), batch.column("wc").take(of)], names=["block", "a", "wa", "c", "wc"])

    def multiply(t: pa.Table) -> pa.Table:
        (a, size), (wa, _), (c, many), (wc, _) = (flat(t.column(x)) for x in ("a", "wa", "c", "wc"))
        row = np.repeat(np.arange(len(size)), size)
        p = wc / np.repeat(np.add.reduceat(wc, np.cumsum(many) - many), many)
        order = np.argsort(a, kind="stable")
        (ua, at), (uc, to) = np.unique(a[order], return_inverse=True), np.unique(c, return_inverse=True)
        wa, row = wa[order], row[order]
        upto = np.cumsum(many[row])  # products up to each entry
        ends = np.r_[np.flatnonzero(at[1:] != at[:-1]) + 1, len(at)]  # entries up to each source
        out, lo = [[], [], [], []], 0
        start = np.cumsum(many) - many
        while lo < len(ua):
            e0 = ends[lo - 1] if lo else 0
            done = upto[e0 - 1] if e0 else 0
            hi = min(max(lo + 1, int(np.searchsorted(upto[ends - 1], done + 1_000_000, side="right"))), lo + max(1, 4_000_000 // len(uc)))
            sums = np.zeros((hi - lo) * len(uc))
            while e0 < ends[hi - 1]:
                e1 = min(max(e0 + 1, int(np.searchsorted(upto, (upto[e0 - 1] if e0 else 0) + 1_000_000, side="right"))), int(ends[hi - 1]))
                k = many[row[e0:e1]]
                here = np.repeat(np.arange(e0, e1), k)
                there = np.arange(len(here)) - np.repeat(np.cumsum(k) - k, k) + start[row[here]]
                sums += np.bincount((at[here] - lo) * len(uc) + to[there], weights=wa[here] * p[there], minlength=len(sums))
                e0 = e1
            hit = np.flatnonzero(sums)
            total = sums.reshape(hi - lo, -1).sum(axis=1)
            for o, v in zip(out, (ua[lo + hit // len(uc)], uc[hit % len(uc)], sums[hit], sums[hit] / total[hit // len(uc)]), strict=True):
                o.append(v)
            lo = hi
        return pa.table([pa.array(np.concatenate(o)) for o in out], names=["src", "dst", "w", "prob"])

    return both.mapInArrow(deal, "block int, a array<long>, wa array<double>, c array<long>, wc array<double>").groupBy("block").applyInArrow(multiply, "src long, dst long, w double, prob double")


def cosine(a: Column, b: Column) -> Column:
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)
    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


def _nearest(placed: DataFrame, k: int) -> DataFrame:
    """placed (bucket, home, blocks, home_blocks, id, v) to the symmetrised ``k`` nearest of each id among the vectors at home in its buckets.

    Vectors travel to the cells of a bucket's block grid and meet in numpy, which keeps only ``k`` candidates for each row
    of a cell: ``home_blocks`` copies of a vector are shuffled (``blocks`` of one at home), never pairs, and a task holds two blocks.
    """
    import numpy as np
    import pyarrow as pa

    part = lambda n: F.pmod(F.xxhash64("id"), F.col(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    left = placed.select("bucket", "id", "v", part("blocks").alias("i"), every("home_blocks").alias("j")).withColumn("side", F.lit(0))
    right = placed.where("home").select("bucket", "id", "v", every("blocks").alias("i"), part("home_blocks").alias("j")).withColumn("side", F.lit(1))

    def cell(t: pa.Table) -> pa.Table:
        side, ids = t.column("side").to_numpy(), t.column("id").to_numpy()
        v = np.array(t.column("v").to_pylist(), np.float64).reshape(len(ids), -1)
        v = v / np.maximum(np.sqrt((v * v).sum(axis=1)), 1e-300)[:, None]
        a, b = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
        out = [[], [], []]
        if len(a) and len(b):
            b = b[np.argsort(ids[b], kind="stable")]
            for at in range(0, len(a), 1024):
                rows = a[at : at + 1024]
                s = np.round(v[rows] @ v[b].T, 12)
                s[ids[rows][:, None] == ids[b][None, :]] = -np.inf
                top = np.argsort(-s, axis=1, kind="stable")[:, :k]
                out[0].append(np.repeat(ids[rows], top.shape[1]))
                out[1].append(ids[b][top].reshape(-1))
                out[2].append(np.take_along_axis(s, top, axis=1).reshape(-1))
        cols = [np.concatenate(x) if x else np.zeros(0) for x in out]
        keep = np.isfinite(cols[2])
        return pa.table([pa.array(cols[0][keep].astype(np.int64)), pa.array(cols[1][keep].astype(np.int64)), pa.array(cols[2][keep])], names=["src", "dst", "w"])

    near = left.unionByName(right).groupBy("bucket", "i", "j").applyInArrow(cell, "src long, dst long, w double").distinct()
    rank = F.row_number().over(Window.partitionBy("src").orderBy(F.desc("w"), "dst"))
    top = near.withColumn("rank", rank).where(F.col("rank") <= k).select("src", "dst", F.greatest("w", F.lit(1e-12)).alias("w"))
    return top.unionByName(top.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w")).groupBy("src", "dst").agg(F.max("w").alias("w"))


def _vectors(emb: DataFrame, id_col: str, vec: str) -> DataFrame:
    return emb.select(F.col(id_col).cast("long").alias("id"), F.col(vec).cast("array<double>").alias("v")).where("id is not null and v is not null")


def knn(emb: DataFrame, k: int, id_col: str = "vec_id", vec: str = "embedding", blocks: int | None = None) -> DataFrame:
    """(src, dst, w): each vector's ``k`` nearest by cosine (ties: the lesser id), symmetrised by the maximum; exact."""
    base = _vectors(emb, id_col, vec)
    n = blocks or max(1, -(-base.count() // KNN_BLOCK))
    return _nearest(base.select(F.lit(0).alias("bucket"), F.lit(True).alias("home"), F.lit(n).alias("blocks"), F.lit(n).alias("home_blocks"), "id", "v"), k)


def knn_lsh(emb: DataFrame, k: int, planes: int = 8, tables: int = 8, id_col: str = "vec_id", vec: str = "embedding", seed: int = 7, probes: int = 20) -> DataFrame:
    """Approximate ``knn`` for sets too large for one grid: buckets of orthonormal hyperplanes, exact ranking within a bucket; large
    buckets are grids of blocks themselves.

    A vector is at home in one bucket of each table and looks into ``probes`` of them, those whose sides it is nearest to. Every vector
    is then compared with ``tables * probes / 2**planes`` of the set at most; neighbours of low cosine need a large part of it.
    """
    import numpy as np
    import pyarrow as pa

    base = _vectors(emb, id_col, vec)
    first = base.first()
    size, probes = len(first["v"]) if first else 1, min(probes, 1 << planes)
    normals = np.random.default_rng(seed).normal(size=(tables * planes, max(1, size)))
    normals = np.vstack([np.linalg.qr(normals[at : at + max(1, size)].T)[0].T for at in range(0, len(normals), max(1, size))])
    sides = np.array([[1.0 if code >> p & 1 else -1.0 for p in range(planes)] for code in range(1 << planes)])

    def look(batches):
        for batch in batches:
            if batch.num_rows == 0:
                continue
            v = np.array(batch.column("v").to_pylist(), np.float64).reshape(batch.num_rows, -1)
            found = []
            for t in range(tables):
                far = -(v @ normals[t * planes : (t + 1) * planes].T) @ sides.T
                found.append(np.argsort(far, axis=1, kind="stable")[:, :probes] + (t << planes))
            buckets = pa.array(list(np.hstack(found).astype(np.int64)), pa.list_(pa.int64()))
            yield pa.RecordBatch.from_arrays([batch.column("id"), batch.column("v"), buckets], names=["id", "v", "buckets"])

    looked = base.mapInArrow(look, "id long, v array<double>, buckets array<long>").select("id", "v", F.posexplode("buckets").alias("at", "bucket"))
    placed = looked.select("id", "v", "bucket", (F.col("at") % probes == 0).alias("home"))
    blocks = lambda n: F.ceil(n / KNN_BLOCK).cast("int")
    sizes = placed.groupBy("bucket").agg(blocks(F.count("*")).alias("blocks"), F.greatest(blocks(F.count_if("home")), F.lit(1)).alias("home_blocks"))
    return _nearest(placed.join(sizes, "bucket"), k)


def regional(lineitem: DataFrame, orders: DataFrame, customer: DataFrame, supplier: DataFrame, nation: DataFrame, eps: float) -> DataFrame:
    """(src, dst, w): lines from a customer's nation to a supplier's, weights across regions multiplied by ``eps``.

    One large join (lines with orders); nations and suppliers are small and left to the planner's broadcast threshold.
    """
    by_pair = lineitem.select("l_orderkey", "l_suppkey").groupBy("l_orderkey", "l_suppkey").agg(F.count("*").alias("n"))
    flow = (
        by_pair.join(orders.select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey"), "l_orderkey")
        .join(customer.select(F.col("c_custkey").alias("o_custkey"), F.col("c_nationkey").cast("long").alias("src")), "o_custkey")
        .join(supplier.select(F.col("s_suppkey").alias("l_suppkey"), F.col("s_nationkey").cast("long").alias("dst")), "l_suppkey")
        .groupBy("src", "dst").agg(F.sum("n").alias("n"))
    )
    region = lambda c: nation.select(F.col("n_nationkey").cast("long").alias(c), F.col("n_regionkey").alias(f"r_{c}"))
    placed = flow.join(region("src"), "src").join(region("dst"), "dst")
    return placed.select("src", "dst", F.when(F.col("r_src") == F.col("r_dst"), F.col("n").cast("double")).otherwise(F.col("n") * F.lit(float(eps))).alias("w"))


def host_links(pages: DataFrame) -> DataFrame:
    """(src, dst, w): host of a page's url and each link target in its html, with multiplicity."""
    host = F.regexp_extract("url", r"^[^:]+://([^/?#]*)", 1)
    links = F.explode(F.regexp_extract_all("html", F.lit(r'href="([^"]*)"'), F.lit(1)))
    return pages.select(F.concat(F.lit("h:"), host).alias("src"), links.alias("link")).groupBy("src", F.concat(F.lit("p:"), "link").alias("dst")).agg(F.count("*").cast("double").alias("w"))


def _words(text: str) -> Column:
    return F.regexp_extract_all(F.lower(F.coalesce(F.col(text), F.lit(""))), F.lit(r"[a-z0-9_\u0080-￿]+"), F.lit(0))


def word_succession(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(src, dst, w): words and the next word of their document, the last followed by the first; without a shuffle of positions.

    A document's pairs are made within its row; only counted pairs travel.
    """
    words = _words(text)
    d = docs.select(words.alias("w")).where(F.size("w") > 0)
    nxt = F.concat(F.slice("w", F.lit(2), F.size("w")), F.slice("w", 1, 1))
    pairs = d.select(F.explode(F.arrays_zip(F.col("w").alias("a"), nxt.alias("b"))).alias("p"))
    return pairs.select(F.col("p.a").alias("src"), F.col("p.b").alias("dst")).groupBy("src", "dst").agg(F.count("*").cast("double").alias("w"))


def word_chain(docs: DataFrame, text: str = "text") -> SuccessionChain:
    """The chain of ``word_succession`` as sequences of the words' hashes; where two words share one, another seed is taken."""
    words = written(docs.select(F.explode(_words(text)).alias("label")).groupBy("label").agg(F.count("*").alias("visits")), "words")
    for seed in range(64):
        hashed = lambda c: F.xxhash64(c, F.lit(seed))  # noqa: B023, E731
        states = words.select(hashed(F.col("label")).alias("state"), "label", "visits")
        if states.groupBy("state").count().where("count > 1").isEmpty():
            return SuccessionChain(docs.select(F.transform(_words(text), hashed).alias("ids")), states, "words")
    raise ValueError("no seed tells the words apart")
