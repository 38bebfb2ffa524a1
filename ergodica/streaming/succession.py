"""Streams: live transition counts, windowed chains, and stationary vectors that follow the counts."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle, StreamingQuery
from pyspark.sql.types import StructType

PAIRS = "key string, src string, dst string, ts timestamp, w long"
MARGIN_MS = 86_400_000  # beyond the watermark: a zone's offset, or a silent key's stay


def read_events(spark: SparkSession, path: str, schema: StructType | str, files_a_trigger: int = 4) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_a_trigger).parquet(path)


def _held(order: T.DataType) -> T.StructType:
    """A key's state: time, order and state of its events, by rising time."""
    return T.StructType([T.StructField(n, T.ArrayType(t)) for n, t in (("at", T.LongType()), ("order", order), ("state", T.StringType()))])


def _merge(key: str, held: tuple | None, batches: Iterator[pd.DataFrame], watermark_ms: int) -> tuple[tuple, pd.DataFrame]:
    """A key's held events and the new ones to what is held next, and the pairs that come (w = 1) and go (w = -1)."""
    rows = pd.concat(list(batches))
    rows = rows[rows["ts"].notna()]
    old = [(*e, False) for e in zip(*held, strict=True)] if held else []
    new = zip((t.value // 1000 for t in rows["ts"].astype("datetime64[ns]")), rows["order"].tolist(), (None if pd.isna(x) else x for x in rows["state"]), strict=True)
    merged = sorted(old + [(*e, True) for e in new], key=lambda e: e[:2])
    out, last = [], None
    for p, q in zip([None, *merged], merged, strict=False):
        if p and (p[3] or q[3]):
            out.append((p[2], q[2], q[0], 1))
        if p and p[3] and not q[3] and last:
            out.append((last[2], q[2], q[0], -1))
        last = last if q[3] else q
    open_ = next((i for i, e in enumerate(merged) if e[0] > (watermark_ms - MARGIN_MS) * 1000), len(merged))
    kept = merged[max(0, open_ - 1) :]  # a later row can still follow the last event before the watermark
    pairs = pd.DataFrame({"key": key, "src": [x[0] for x in out], "dst": [x[1] for x in out], "ts": pd.to_datetime([x[2] for x in out], unit="us"), "w": pd.Series([x[3] for x in out], dtype="int64")}, index=range(len(out)))
    return tuple([e[i] for e in kept] for i in range(3)), pairs


def pairs_with_state(stream: DataFrame, key: str, ts: str, state: str, watermark: str | None = "2 hours", order: str | None = None) -> DataFrame:
    """key, src, dst, ts, w of successive events of each key, by ``applyInPandasWithState``.

    The state is a key's events since the watermark and the last one before it. An event that is earlier than others seen is put
    in its place: the pair that it parts is taken back by a row of ``w`` -1, so sums of ``w`` are those of the events in time order.
    Equal times are ordered by ``order`` (no nulls), or by arrival. Rows without a time are left out. Rows later than the watermark are dropped by
    Spark (``dropped`` counts them); a key silent for a day beyond it is forgotten. ``watermark`` None: the stream has one already
    (``deduplicated``).
    """

    def follow(keys, batches: Iterator[pd.DataFrame], group) -> Iterator[pd.DataFrame]:
        if group.hasTimedOut:
            group.remove()
            return
        held, pairs = _merge(keys[0], group.get if group.exists else None, batches, group.getCurrentWatermarkMs())
        if held[0]:
            group.update(held)
            group.setTimeoutTimestamp(max(int(held[0][-1] // 1000) + MARGIN_MS, group.getCurrentWatermarkMs() + 1))
        yield pairs

    slim = _slim(stream, key, ts, state, order, watermark)
    slim = slim.withWatermark("ts", watermark) if watermark else slim
    return slim.groupBy("key").applyInPandasWithState(follow, PAIRS, _held(slim.schema["order"].dataType), "append", "EventTimeTimeout")


def _slim(stream: DataFrame, key: str, ts: str, state: str, order: str | None, watermark: str | None) -> DataFrame:
    at = F.col(ts).cast("timestamp") if watermark else F.col(ts)
    return stream.select(F.col(key).cast("string").alias("key"), at.alias("ts"), F.col(state).cast("string").alias("state"), (F.col(order) if order else F.lit(0)).alias("order"))


class Follow(StatefulProcessor):
    """The same with ``transformWithStateInPandas`` and a value state."""

    def __init__(self, order: T.DataType) -> None:
        self.order = order

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle, self.held = handle, handle.getValueState("held", _held(self.order))

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timers) -> Iterator[pd.DataFrame]:
        held, pairs = _merge(key[0], self.held.get() if self.held.exists() else None, rows, timers.getCurrentWatermarkInMs())
        self.held.update(held)
        for old in list(self.handle.listTimers()):
            self.handle.deleteTimer(old)
        if held[0]:
            self.handle.registerTimer(max(int(held[0][-1] // 1000) + MARGIN_MS, timers.getCurrentWatermarkInMs() + 1))
        yield pairs

    def handleExpiredTimer(self, key, timers, expired) -> Iterator[pd.DataFrame]:
        """A key silent for a day beyond the watermark is forgotten."""
        self.held.clear()
        return iter(())

    def close(self) -> None:
        pass


def pairs_with_processor(stream: DataFrame, key: str, ts: str, state: str, watermark: str = "2 hours", order: str | None = None) -> DataFrame:
    """Needs the RocksDB state store provider to be set in the session."""
    slim = _slim(stream, key, ts, state, order, watermark).withWatermark("ts", watermark)
    return slim.groupBy("key").transformWithStateInPandas(Follow(slim.schema["order"].dataType), PAIRS, "Append", "EventTime")


def dropped(query: StreamingQuery) -> int:
    """Rows that came later than the watermark, over the progress the session keeps (``spark.sql.streaming.numRecentProgressUpdates``)."""
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])


def weight(pairs: DataFrame) -> Column:
    """The pairs' number: the sum of ``w`` where they have it."""
    return F.sum("w") if "w" in pairs.columns else F.count("*")


def succession_counts(pairs: DataFrame) -> DataFrame:
    """Running counts (update or complete mode)."""
    return pairs.groupBy("src", "dst").agg(weight(pairs).alias("w"))


def windowed_chain(pairs: DataFrame, window: str = "1 day", slide: str | None = None, watermark: str = "2 hours") -> DataFrame:
    """start, src, dst, w for tumbling or sliding windows; append mode gives closed windows.

    ``pairs`` is a stream of written pairs (src, dst, ts, and w if they have it): a second stateful step in one query would need a second watermark.
    """
    span = F.window("ts", window, slide) if slide else F.window("ts", window)
    return pairs.withWatermark("ts", watermark).groupBy(span.alias("span"), "src", "dst").agg(weight(pairs).alias("w")).select(F.col("span.start").alias("start"), "src", "dst", "w")


def session_chain(stream: DataFrame, key: str, ts: str, gap: str = "30 minutes", watermark: str = "2 hours") -> DataFrame:
    """Session lengths of each key: key, start, end, events."""
    return stream.withWatermark(ts, watermark).groupBy(F.session_window(ts, gap).alias("s"), key).agg(F.count("*").alias("events")).select(key, F.col("s.start").alias("start"), F.col("s.end").alias("end"), "events")


def deduplicated(stream: DataFrame, ident: str, ts: str, watermark: str = "2 hours") -> DataFrame:
    return stream.withWatermark(ts, watermark).dropDuplicatesWithinWatermark([ident])


def followed_by(a: DataFrame, b: DataFrame, key: str, ts: str, within: str = "1 hour", watermark: str = "2 hours") -> DataFrame:
    """Stream-stream interval join: events of ``a`` with events of ``b`` of the same key at most ``within`` later."""
    left, right = a.withWatermark(ts, watermark).alias("a"), b.withWatermark(ts, watermark).alias("b")
    on = (F.col(f"a.{key}") == F.col(f"b.{key}")) & (F.col(f"b.{ts}") > F.col(f"a.{ts}")) & (F.col(f"b.{ts}") <= F.col(f"a.{ts}") + F.expr(f"interval {within}"))
    return left.join(right, on).select(F.col(f"a.{key}").alias(key), F.col(f"a.{ts}").alias("ts_a"), F.col(f"b.{ts}").alias("ts_b"))


class Refresher:
    """For ``foreachBatch``: adds a batch's counts to those held and solves again from the last vector.

    Everything is in files: counts (one row for each pair of states) under ``path``-counts, vectors (state, pi, iterations) under ``path``, a folder for each
    epoch. An epoch always starts from the latest one before it and replaces its own folders, so a replay counts nothing twice and a restart
    goes on where the files end. The engine is the planner's choice; states without exits spread their mass over all.
    """

    def __init__(self, path: str, width: int = 4, tol: float = 1e-10):
        self.path, self.counts, self.width, self.tol = path, f"{path}-counts", width, tol

    @staticmethod
    def _epochs(spark: SparkSession, path: str) -> list[int]:
        at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{path}/epoch=*")
        found = at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).globStatus(at)
        return sorted(int(f.getPath().getName().split("=")[1]) for f in found or [])

    def _remove(self, spark: SparkSession, path: str) -> None:
        at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)

    def __call__(self, batch: DataFrame, epoch: int) -> None:
        from ..operators import chain as chains
        from ..operators.solve import solve

        spark = batch.sparkSession
        earlier = [e for e in self._epochs(spark, self.counts) if e < epoch]
        new = batch.groupBy("src", "dst").agg(weight(batch).cast("double").alias("w"))
        if earlier:
            new = spark.read.parquet(f"{self.counts}/epoch={earlier[-1]}").unionByName(new).groupBy("src", "dst").agg(F.sum("w").alias("w"))
        new.write.mode("overwrite").parquet(f"{self.counts}/epoch={epoch}")
        for e in earlier[:-1]:  # a replay needs the one before it only
            self._remove(spark, f"{self.counts}/epoch={e}")
        chain = chains.from_weights(spark.read.parquet(f"{self.counts}/epoch={epoch}"), "stream")
        n = chain.states.count()
        if not n:
            return
        start = "random"
        if solved := [e for e in self._epochs(spark, self.path) if e < epoch]:
            last = spark.read.parquet(f"{self.path}/epoch={solved[-1]}").select(F.col("state").alias("label"), F.col("pi").alias("x0"))
            start = chain.states.join(last, "label").select("state", "x0")
        r = solve(chains.fix_dangling(chain, "uniform"), min(self.width, n), tol=self.tol, check_every=2, seed=epoch, start=start)
        r.pi.select(F.col("label").alias("state"), "pi", F.lit(int(r.ledger.iterations)).cast("long").alias("iterations")).write.mode("overwrite").parquet(f"{self.path}/epoch={epoch}")
