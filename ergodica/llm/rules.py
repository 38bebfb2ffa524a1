"""Quality rules: base counts of a text, and its divergence from language references; DataFrame operations only.

*Divergence.* A text's histogram of character kinds and its histogram of common words are compared with those of every
language by the Jensen-Shannon distance (root of the divergence in bits, 0 to 1); the nearest language counts. References
are statistics of the whole corpus: all words of all documents are counted by language, the ``COMMON`` most frequent of each language
form the word histogram (the rest of the words is one more bin), and character kinds are summed by language. Texts of fewer than
``LEAST_WORDS`` words are not compared (a short text's histogram says little).

Word counts are combined before they are shuffled. A text's own windows and lines are compared within its row, so a long or hot
document never travels; the features are written once and read for the references and the verdict.

Defined results. Null or empty text: all counts 0, base_failed, not kept. Null lang: no part of the references. No language at
all: distances 0. Repeated rows and null ids: each row is judged. Ties among common words: the lesser word. Extra columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import SPACE_CLASS, WORD, slim, written

COMMON = 25
LEAST_WORDS = 50
MOST_KIND, MOST_WORD = 0.4, 0.45
KINDS = ("lower", "upper", "digit", "space", "other", "beyond")
SYMBOLS = r"[^#*$%&|<>]+"
_PLACE = 24  # low bits of a window's key: its position


def words(text: Column) -> Column:
    return F.array_remove(F.split(text, f"[{SPACE_CLASS}]+"), "")


def _left(text: Column, gone: str) -> Column:
    return F.length(F.regexp_replace(text, gone, "")).cast("long")


def _neighbours(array: str, same) -> Column:
    """The elements of a sorted array that equal a neighbour under ``same``."""
    at = lambda k: F.get(F.col(array), k)
    return F.filter(F.col(array), lambda x, k: F.coalesce((k > 0) & same(x, at(k - 1)), F.lit(False)) | F.coalesce(same(x, at(k + 1)), F.lit(False)))


def base_counts(docs: DataFrame, keep: list[str], common: list[str] | None = None) -> DataFrame:
    """keep, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, the kinds' counts[, common: the occurrences of common words]."""
    text = F.coalesce(F.col("text"), F.lit(""))
    a = docs.select(*keep, text.alias("text"), words(text).alias("w"))
    kinds = {"lower": "[^a-z]+", "upper": "[^A-Z]+", "digit": "[^0-9]+", "beyond": r"[\x00-\x7F]+"}
    lines = F.filter(F.split("text", "\n"), lambda x: x.rlike(WORD))
    b = a.select(
        *keep, "w", F.size("w").cast("long").alias("n_words"), F.length("text").cast("long").alias("n"), _left(F.col("text"), f"[{SPACE_CLASS}]+").alias("word_chars"), _left(F.col("text"), SYMBOLS).alias("n_symbols"),
        *(_left(F.col("text"), p).alias(k) for k, p in kinds.items()), lines.alias("lines"), F.transform("w", lambda x: F.xxhash64(x)).alias("h"),
        *([F.filter("w", lambda x: F.lower(x).isin(*common)).alias("common")] if common else [F.array().cast("array<string>").alias("common")] if common is not None else []),
    )
    span = F.when(F.col("n_words") >= 3, F.sequence(F.lit(0), (F.col("n_words") - 3).cast("int"))).otherwise(F.array().cast("array<int>"))
    h = lambda i: F.get(F.col("h"), i)
    carried = [*keep, "n_words", "n", "word_chars", "n_symbols", *kinds, *(["common"] if common is not None else [])]
    dup = (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines")
    keyed = F.transform(span, lambda i: F.shiftleft(F.xxhash64(h(i), h(i + 1), h(i + 2)), _PLACE).bitwiseOR(i.cast("long")))
    c = b.select(*carried, dup, "w", F.sort_array(keyed).alias("keys"))
    next_too = F.zip_with("keys", F.slice("keys", F.lit(2), F.size("keys")), lambda x, y: F.shiftright(x, _PLACE) == F.shiftright(y, _PLACE))
    c = c.select("*", next_too.alias("next_too"))
    beside = F.filter("keys", lambda x, k: F.coalesce(F.get("next_too", k), F.lit(False)) | F.coalesce(F.get("next_too", k - 1), F.lit(False)))
    alike = F.when(F.array_contains("next_too", True), beside).otherwise(F.array().cast("array<bigint>"))
    place = F.transform(alike, lambda x: x.bitwiseAND(F.lit((1 << _PLACE) - 1)).cast("int"))
    some = F.when(F.col("n_words") < 1 << _PLACE, place).otherwise(F.sequence(F.lit(0), F.greatest((F.col("n_words") - 3).cast("int"), F.lit(0))))
    word = lambda i: F.get(F.col("w"), i)
    windows = F.transform(some, lambda i: F.struct(F.concat_ws(" ", word(i), word(i + 1), word(i + 2)).alias("s"), i.alias("i")))
    d = c.select(*carried, "n_dup_lines", F.sort_array(windows).alias("windows"))  # equal hashes so far: now the words themselves
    equal = _neighbours("windows", lambda x, y: x["s"] == y["s"])
    e = d.select(*carried, "n_dup_lines", F.sort_array(F.transform(equal, lambda x: x["i"])).alias("starts"))
    each = F.transform("starts", lambda p, k: F.least(F.coalesce(F.get(F.col("starts"), k + 1) - p, F.lit(3)), F.lit(3)))
    repeat = F.aggregate(each, F.lit(0), lambda s, x: s + x).cast("long").alias("n_repeat_words")
    space = (F.col("n") - F.col("word_chars")).alias("space")
    other = (F.col("word_chars") - F.col("lower") - F.col("upper") - F.col("digit") - F.col("beyond")).alias("other")
    return e.select(*keep, "n_words", "word_chars", "n_symbols", "n_dup_lines", repeat, "lower", "upper", "digit", "beyond", space, other, *(["common"] if common is not None else []))


def common_words(docs: DataFrame, common: int = COMMON) -> list[tuple[str, str, float]]:
    """(lang, word, share of the language's words) of each language's most frequent words, over all documents.

    What reaches the driver: ``common`` rows for each language.
    """
    each = slim(docs, "text", "lang").where("lang is not null and text is not null").select("lang", F.explode(F.split("text", f"[{SPACE_CLASS}]+")).alias("word")).where("word <> ''")
    counts = each.select("lang", F.lower("word").alias("word")).groupBy("lang", "word").agg(F.count("*").alias("n"))
    rank = F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "word"))
    total = counts.groupBy("lang").agg(F.sum("n").alias("total"))
    top = counts.withColumn("rank", rank).where(F.col("rank") <= common).join(F.broadcast(total), "lang")
    return sorted((r.lang, r.word, r.n / r.total) for r in top.select("lang", "word", "n", "total").collect())


def _half(p: Column, q: Column) -> Column:
    """One bin's part of the Jensen-Shannon divergence in bits."""
    m = (p + q) / 2
    part = lambda x: F.when(x > 0, x * F.log2(x / m)).otherwise(0.0)
    return (part(p) + part(q)) / 2


def _distance(divergence: Column) -> Column:
    return F.round(F.sqrt(F.greatest(divergence, F.lit(0.0))), 6)


def judge(docs: DataFrame, most_kind: float = MOST_KIND, most_word: float = MOST_WORD, least_words: int = LEAST_WORDS) -> DataFrame:
    """doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept, kind_distance, word_distance."""
    refs = common_words(docs)
    langs = sorted({r[0] for r in refs})
    listed = sorted({r[1] for r in refs})
    share = {(lang, w): q for lang, w, q in refs}
    marked = slim(docs, "doc_id", "text", "lang").withColumn("row", F.monotonically_increasing_id())
    table = written(base_counts(marked, ["row", "doc_id", "lang"], listed), "features")

    sums = {r.lang: r for r in table.where(F.col("lang").isNotNull()).groupBy("lang").agg(*(F.sum(k).alias(k) for k in KINDS)).collect()}
    n = sum((F.col(k) for k in KINDS), F.lit(0))
    kind = []
    for lang in langs:
        whole = max(1, sum(sums[lang][k] for k in KINDS))
        kind.append(_distance(sum((_half(F.col(k) / n, F.lit(sums[lang][k] / whole)) for k in KINDS), F.lit(0.0))))

    full, word = table, []
    if langs:
        spark = docs.sparkSession
        found = table.where("n_words > 0").select("row", "n_words", F.explode("common").alias("word")).groupBy("row", "n_words", F.lower("word").alias("word")).agg(F.count("*").alias("c"))
        known = spark.createDataFrame([(w, *(share.get((lang, w), 0.0) for lang in langs)) for w in listed], "word string" + "".join(f", q{i} double" for i in range(len(langs))))
        p = F.col("c") / F.col("n_words")
        # a bin without words in the text gives q / 2; so sum what the present bins differ by
        terms = found.join(F.broadcast(known), "word").select("row", *(F.when(F.col(f"q{i}") > 0, p).otherwise(0.0).alias(f"p{i}") for i in range(len(langs))), *(F.when(F.col(f"q{i}") > 0, _half(p, F.col(f"q{i}")) - F.col(f"q{i}") / 2).otherwise(0.0).alias(f"t{i}") for i in range(len(langs))))
        by_row = terms.groupBy("row").agg(*(F.sum(f"{x}{i}").alias(f"{x}{i}") for x in "pt" for i in range(len(langs))))
        for i, lang in enumerate(langs):
            all_q = math.fsum(q for (a, _), q in share.items() if a == lang)
            present, mass = F.coalesce(F.col(f"t{i}"), F.lit(0.0)), F.coalesce(F.col(f"p{i}"), F.lit(0.0))
            rest = _half(F.greatest(1 - mass, F.lit(0.0)), F.lit(max(0.0, 1 - all_q)))
            word.append(_distance(present + all_q / 2 + rest))
        full = table.join(by_row, "row", "left")
    long_enough = F.col("n_words") >= least_words
    nearest = lambda d: F.when(long_enough, F.least(*d) if len(d) > 1 else d[0]).otherwise(0.0) if d else F.lit(0.0)
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    judged = full.withColumns({"kind_distance": nearest(kind), "word_distance": nearest(word), "base_failed": failed})
    kept = ~F.col("base_failed") & (F.col("kind_distance") <= most_kind) & (F.col("word_distance") <= most_word)
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", kept.alias("kept"), "kind_distance", "word_distance")
