"""Benchmark decontamination by spaced-seed hashing; DataFrame operations only.

A *seed* is the hash of the words that a fixed mask keeps out of ``SPAN`` consecutive words; what stands at the ignored
positions may differ. Seeds of the benchmark join seeds of the documents; around each hit the document is laid against the
benchmark item along the hit's diagonal and the matching words are counted, so substituted words are tolerated anywhere. Diagonals of
one item at most ``REACH`` apart are also laid together, so words inserted or left out between hits are tolerated too.

A document is contaminated by an item if a run of the laid words covers at least ``least_words`` words, at least ``least_share`` of the
run's words are equal, and the equal words are ``RUN_WORDS``, or ``least_share`` of a shorter item; or if the overlap along a diagonal
covers at least ``least_words`` words and ``least_share`` of the item, and at least ``least_share`` of the overlap's words are equal.

The benchmark's seeds are broadcast only while they are at most ``BROADCAST_SEEDS`` (some 64 MB); beyond that the same join
runs by shuffle, and documents send only their seeds. Hits (document, item, diagonal) are written, and the documents that have
any are read again for the comparison: no text is shuffled while the hits are few enough to broadcast. Copies of a passage meet the item's seeds, never each other, so
nothing grows with the square of a group.

Masks find what the rule accepts with high probability only: README states the recall measured.

Words are lower-cased runs of letters and digits. Defined results. Null or empty text, texts shorter than a span: not
contaminated. Items shorter than a span are matched whole, by exact equality of consecutive words (their seed is the full item). Null
ids: kept, matched like others. Null benchmark text: no seeds. Repeated rows: each judged. Extra columns are ignored or carried.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import slim, written

SPAN = 11
# Positions that each mask keeps: weight 7 of a span of 11, and weight 4 of shorter spans for words substituted densely.
MASKS = ((0, 1, 2, 4, 7, 9, 10), (0, 2, 3, 5, 6, 8, 10), (0, 1, 4, 5, 6, 9, 10), (0, 2, 3, 6), (0, 3, 4, 5), (0, 2, 7, 8))
SHORTEST = min(mask[-1] for mask in MASKS) + 1
BROADCAST_SEEDS = 1_000_000
REACH = 8  # words inserted or left out between two hits of one copy, at most
RUN_WORDS = 13  # equal words in one run that contaminate, whatever the item's length


def word_hashes(text: Column) -> Column:
    """Hashes of the lower-cased runs of letters and digits."""
    words = F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+"), lambda w: w != "")
    return F.transform(words, lambda w: F.xxhash64(w))


def seeds(array: str, at: Column) -> Column:
    """The masks' seeds of the spans that start at ``at``; null for a mask that reaches beyond the end."""
    ends = F.size(array)
    return F.array(*(F.when(at + mask[-1] < ends, F.xxhash64(F.lit(m), *(F.get(F.col(array), at + p) for p in mask))) for m, mask in enumerate(MASKS)))


def _spans(df: DataFrame, keep: list[str], array: str) -> DataFrame:
    """keep, array, at, seed: every seed of every span."""
    placed = df.where(F.size(array) >= SPAN).select(*keep, array, F.explode(F.sequence(F.lit(0), F.size(array) - SHORTEST)).alias("at"))
    return placed.select(*keep, array, "at", F.explode(seeds(array, F.col("at"))).alias("seed")).where("seed is not null")


def contaminations(docs: DataFrame, benchmark: DataFrame, least_words: int = SPAN, least_share: float = 0.6) -> DataFrame:
    """row, item_id, matched, overlap for each (document, item) found; ``docs`` needs doc_id and text.

    ``row`` identifies the document by id and text hash, so repeated ids do not mix.
    """
    items = slim(benchmark, "item_id", "text").select("item_id", word_hashes(F.col("text")).alias("item")).where(F.size("item") > 0)
    item_seeds = _spans(items, ["item_id"], "item").select("item_id", F.col("at").alias("item_at"), "seed").distinct()
    small = item_seeds.limit(BROADCAST_SEEDS + 1).count() <= BROADCAST_SEEDS
    texts = slim(docs, "doc_id", "text").select("doc_id", F.xxhash64("text").alias("text_hash"), word_hashes(F.col("text")).alias("words"))
    doc_seeds = _spans(texts, ["doc_id", "text_hash"], "words").select("doc_id", "text_hash", "at", "seed")
    hits = doc_seeds.join(F.broadcast(item_seeds) if small else item_seeds, "seed")
    hits = written(hits.select("doc_id", "text_hash", "item_id", (F.col("at") - F.col("item_at")).alias("diagonal")).distinct(), "hits")
    few = hits.limit(BROADCAST_SEEDS + 1).count() <= BROADCAST_SEEDS
    named = _lays(hits).withColumnsRenamed({"doc_id": "__d", "text_hash": "__h"})
    same = F.col("doc_id").eqNullSafe(F.col("__d")) & F.col("text_hash").eqNullSafe(F.col("__h"))
    keyed = slim(docs, "doc_id", "text").select("doc_id", F.xxhash64("text").alias("text_hash"), "text")
    back = keyed.join(F.broadcast(named) if few else named, same).select("doc_id", "text_hash", "near", word_hashes(F.col("text")).alias("words"))
    back = back.select("doc_id", "text_hash", "words", F.explode("near").alias("near")).select("doc_id", "text_hash", "words", "near.item_id", "near.lays")
    laid = back.join(items, "item_id").select("doc_id", "text_hash", "item_id", "item", "words", F.explode("lays").alias("lay"))
    marked = laid.select("doc_id", "text_hash", "item_id", _marks().alias("marks"))
    whole = F.struct(F.size(F.filter("marks", lambda m: m)).alias("matched"), F.size(F.filter("marks", lambda m: m.isNotNull())).alias("overlap"))
    runs = (_run(F.col("marks"), least_share), _run(F.reverse("marks"), least_share))
    compared = marked.select("doc_id", "text_hash", "item_id", F.size("marks").alias("item_words"), whole.alias("whole"), F.greatest(*runs).alias("run"))
    covers = (F.col("whole.overlap") >= least_words) & (F.col("whole.overlap") >= least_share * F.col("item_words")) & (F.col("whole.matched") >= least_share * F.col("whole.overlap"))
    holds = (F.col("run.overlap") >= least_words) & (F.col("run.matched") >= F.least(F.lit(RUN_WORDS), least_share * F.col("item_words")))
    best = F.max(F.greatest(F.when(covers, F.col("whole")), F.when(holds, F.col("run"))))
    found = compared.where(covers | holds).groupBy("doc_id", "text_hash", "item_id").agg(best.alias("b")).select("doc_id", "text_hash", "item_id", "b.matched", "b.overlap")
    return found.unionByName(_short_items(texts, items))


def _lays(hits: DataFrame) -> DataFrame:
    """doc_id, text_hash, near (item_id, lays): one row for each document, with its groups of diagonals of an item at most ``REACH`` apart; the
    lays of a group are each diagonal alone and, if there are several, all of them together."""
    along = Window.partitionBy("doc_id", "text_hash", "item_id").orderBy("diagonal")
    opens = F.when(F.col("diagonal") - F.lag("diagonal").over(along) <= REACH, 0).otherwise(1)
    grouped = hits.withColumn("opens", opens).withColumn("near", F.sum("opens").over(along))
    sets = grouped.groupBy("doc_id", "text_hash", "item_id", "near").agg(F.collect_list("diagonal").alias("all"))
    single = F.transform("all", lambda d: F.array(d))
    lays = F.when(F.size("all") > 1, F.concat(single, F.array("all"))).otherwise(single)
    return sets.groupBy("doc_id", "text_hash").agg(F.collect_list(F.struct("item_id", lays.alias("lays"))).alias("near"))


def _marks() -> Column:
    """For each word of the item whether the document has it on a diagonal of ``lay``; null beyond the document's ends (one diagonal only)."""
    beyond = F.when(F.size("lay") > 1, False)
    return F.transform("item", lambda w, i: F.coalesce(F.exists("lay", lambda d: F.get(F.col("words"), i + d) == w), beyond))


def _run(marks: Column, share: float) -> Column:
    """matched, overlap of the run with the most equal words that starts where the share before it fell short, and keeps at least ``share``."""
    none = F.struct(F.lit(0).alias("matched"), F.lit(0).alias("overlap"))
    start = F.struct(none.alias("now"), none.alias("best"))

    def step(s: Column, m: Column) -> Column:
        matched, overlap = s["now"]["matched"] + F.when(m, 1).otherwise(0), s["now"]["overlap"] + 1
        now = F.when(matched >= share * overlap, F.struct(matched.alias("matched"), overlap.alias("overlap"))).otherwise(none)
        return F.struct(now.alias("now"), F.when(now["matched"] > s["best"]["matched"], now).otherwise(s["best"]).alias("best"))

    return F.aggregate(marks, start, step, lambda s: s["best"])


def _short_items(texts: DataFrame, items: DataFrame) -> DataFrame:
    """Items shorter than a span: all their words, consecutive and equal, by one seed per length that occurs (SPAN - 1 lengths at most)."""
    short = items.where(F.size("item") < SPAN)
    lengths = sorted(r[0] for r in short.select(F.size("item")).distinct().collect())  # at most SPAN - 1 values
    whole = F.array_join(F.col("item").cast("array<string>"), ",")
    keyed = short.select("item_id", F.size("item").alias("overlap"), whole.alias("seed"))
    if not lengths:
        return _none(texts, items)
    placed = texts.select("doc_id", "text_hash", "words", F.explode(F.array(*map(F.lit, lengths))).alias("n")).where("size(words) >= n")
    each = placed.select("doc_id", "text_hash", "words", "n", F.explode(F.sequence(F.lit(0), F.size("words") - F.col("n"))).alias("at"))
    seeds_ = each.select("doc_id", "text_hash", F.array_join(F.slice("words", F.col("at") + 1, F.col("n")).cast("array<string>"), ",").alias("seed"))
    return seeds_.join(keyed, "seed").select("doc_id", "text_hash", "item_id", F.col("overlap").alias("matched"), "overlap").distinct()


def _none(texts: DataFrame, items: DataFrame) -> DataFrame:
    spark = texts.sparkSession
    kind = items.schema["item_id"].dataType.simpleString()
    return spark.createDataFrame([], f"doc_id {texts.schema['doc_id'].dataType.simpleString()}, text_hash long, item_id {kind}, matched int, overlap int")


def decontaminate(docs: DataFrame, benchmark: DataFrame, least_words: int = SPAN, least_share: float = 0.6) -> DataFrame:
    """doc_id, contaminated, n_items, item_id (of the best overlap, least id on ties), matched, overlap for every row."""
    best = F.max_by(F.struct("item_id", "matched", "overlap"), F.struct("matched", "overlap", -F.col("item_id")))
    found = contaminations(docs, benchmark, least_words, least_share).groupBy("doc_id", "text_hash").agg(F.count("*").alias("n_items"), best.alias("b"))
    found = found.withColumnsRenamed({"doc_id": "__d", "text_hash": "__h"})
    base = slim(docs, "doc_id", "text").select("doc_id", F.xxhash64("text").alias("text_hash"))
    joined = base.join(found, base["doc_id"].eqNullSafe(found["__d"]) & (base["text_hash"] == found["__h"]), "left")
    return joined.select(
        "doc_id", F.col("n_items").isNotNull().alias("contaminated"), F.coalesce("n_items", F.lit(0)).alias("n_items"), F.col("b.item_id").alias("item_id"), F.col("b.matched").alias("matched"), F.col("b.overlap").alias("overlap")
    )


def clean(docs: DataFrame, benchmark: DataFrame, least_words: int = SPAN, least_share: float = 0.6) -> DataFrame:
    """The rows of ``docs`` that no benchmark item contaminates."""
    found = contaminations(docs, benchmark, least_words, least_share).select(F.col("doc_id").alias("__d"), F.col("text_hash").alias("__h")).distinct()
    return docs.join(found, docs["doc_id"].eqNullSafe(found["__d"]) & (F.xxhash64(docs["text"]) == found["__h"]), "left_anti")
