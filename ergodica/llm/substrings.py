"""Exact removal of repeated word windows by super-k-mer partitioning.

A *window* is ``window`` consecutive words of one document. Its minimiser is the word of least rank in it (long words
before short ones, then by hash). Consecutive windows sharing a minimiser travel as one packed string to the minimiser's
bucket; there the windows are sorted and equal neighbours, compared word by word, are the exact repeats.

Before anything travels, each batch of documents sorts its own windows: a window that also starts in a smaller document
of the batch is decided there, and only the batch's first occurrence goes on. So a passage, a line or a group of copies
that a third of all documents hold reaches its bucket once for each batch, not once for each document. All super-k-mers of a
batch for one bucket are one compressed row (about a third of the text's volume in the shuffle).

Rules and defined results. A word is removed if a window covering it has a word sequence that also starts in a document
with a smaller doc_id; windows are judged on the input. Null or empty text: no words. Texts shorter than a window, and rows
with a null doc_id, neither remove nor lose anything. Rows that repeat a doc_id are not smaller than one another. Extra
columns are ignored (``substring_duplicates``) or carried along (``without_repeats``).
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from operator import eq

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import in_batches, slim
from .neardup import mix

WINDOW = 13
SHORT = 4  # words of so many bytes at most are minimisers only where nothing longer is
BUCKETS_A_PARTITION = 6
_PIECE = re.compile(rb"([\x20\x09-\x0D]*)([^\x20\x09-\x0D]+)")


_BY_PLACE = mix(np.arange(1, 4097, dtype=np.uint64))  # multipliers of a word's bytes by their place
_BY_BYTE = mix(np.arange(257, 513, dtype=np.uint64)) | np.uint64(1)
CHUNK = 1 << 20  # bytes hashed at once


class Windows:
    """The windows of several runs of words, sorted so that equal ones stand together, the least document first.

    ``text``: the runs, a line each, words separated by one space; ``docs``: the document of each run, ascending.
    """

    def __init__(self, text: bytes, docs: np.ndarray, window: int):
        self.window, self.text = window, text
        raw = np.frombuffer(text, np.uint8)
        line = raw == 10
        breaks = np.flatnonzero(line | (raw == 32)).astype(np.int32)
        self.start, self.end = np.append(np.int32(0), breaks + np.int32(1)), np.append(breaks, np.int32(len(raw)))
        run = np.append(0, np.cumsum(line[breaks])) if len(docs) else np.zeros(0, np.int64)
        self.start, self.end = self.start[: len(run)], self.end[: len(run)]
        counts = np.maximum(np.bincount(run, minlength=len(docs)) - window + 1, 0)
        first = np.searchsorted(run, np.arange(len(docs)))
        self.run = np.repeat(np.arange(len(docs)), counts)
        self.offset = np.arange(len(self.run)) - np.repeat(np.cumsum(counts) - counts, counts)
        self.at = first[self.run] + self.offset
        self.doc = docs[self.run]
        self.hashes = self._hashes(raw)

    def _hashes(self, raw: np.ndarray) -> np.ndarray:
        """A 64-bit hash of each word's bytes, whatever stands around it."""
        size, out = self.end - self.start, np.zeros(len(self.start), np.uint64)
        a = 0
        while a < len(out):
            b = max(a + 1, int(np.searchsorted(self.end, self.start[a] + CHUNK)))
            base, part = self.start[a], size[a:b]
            place = np.arange(base, self.end[b - 1] + 1, dtype=np.int32) - np.repeat(self.start[a:b], part + 1)
            terms = np.empty(len(place), np.uint64)
            terms[:-1] = _BY_BYTE[raw[base : self.end[b - 1]]]
            terms *= _BY_PLACE[place & 4095]
            if part.max() > 4096:
                terms *= np.where(place >= 4096, place.astype(np.uint64) | np.uint64(1), np.uint64(1))
            terms[self.end[a:b] - base] = 0  # what separates words
            out[a:b] = np.add.reduceat(terms, self.start[a:b] - base)
            a = b
        return mix(out + size.astype(np.uint64))

    def repeats(self) -> np.ndarray:
        """For each window: does it also start in a smaller document?"""
        n = len(self.at)
        if not n:
            return np.zeros(0, bool)
        h = np.zeros(n, np.uint64)
        for j in range(self.window):
            h *= np.uint64(0x9E3779B97F4A7C15)
            h += self.hashes[self.at + j]
        h = mix(h)
        order = np.argsort(h, kind="stable")
        same = h[order][1:] == h[order][:-1]
        if not self._equal(order[1:][same], order[:-1][same]):  # two windows under one hash: sort by the words
            number: dict[bytes, int] = {}
            group = np.fromiter((number.setdefault(x, len(number)) for x in self._bytes(np.arange(n))), np.int64, n)
            order = np.argsort(group, kind="stable")
            same = group[order][1:] == group[order][:-1]
        start = np.flatnonzero(np.concatenate([[True], ~same]))
        least = np.repeat(self.doc[order][start], np.diff(np.append(start, n)))
        out = np.empty(n, bool)
        out[order] = self.doc[order] > least
        return out

    def _bytes(self, windows: np.ndarray) -> Iterator[bytes]:
        at = self.at[windows]
        return (self.text[a:b] for a, b in zip(self.start[at].tolist(), self.end[at + self.window - 1].tolist(), strict=True))

    def _equal(self, a: np.ndarray, b: np.ndarray) -> bool:
        return all(map(eq, self._bytes(a), self._bytes(b)))

    def minimisers(self) -> np.ndarray:
        short = self.end - self.start <= SHORT
        rank = (mix(self.hashes) >> np.uint64(1)) | np.where(short, np.uint64(1 << 63), np.uint64(0))
        least = rank[self.at]
        for j in range(1, self.window):
            np.minimum(least, rank[self.at + j], out=least)
        return least


def _spans(starts: np.ndarray) -> np.ndarray:
    """Ascending window starts to (start, count) of consecutive runs, int32."""
    cut = np.flatnonzero(np.diff(starts, prepend=starts[0] - 2) != 1)
    return np.stack([starts[cut], np.diff(np.append(cut, len(starts)))], axis=1).astype(np.int32)


def _flag_rows(run: np.ndarray, start: np.ndarray, doc: np.ndarray, key: np.ndarray) -> tuple[list, list, list]:
    """Flagged windows, given by run and start, to (doc, key, packed spans) of each run."""
    ids, keys, data = [], [], []
    cut = np.append(np.flatnonzero(np.diff(run, prepend=-1)), len(run))
    for a, b in zip(cut[:-1], cut[1:], strict=True):
        ids.append(int(doc[run[a]]))
        keys.append(int(key[run[a]]))
        data.append(_spans(start[a:b]).tobytes())
    return ids, keys, data


def _sender(window: int, buckets: int):
    def kernel(t: pa.Table) -> Iterator[pa.Table]:
        squeeze = zstandard.ZstdCompressor(level=3)
        t = t.sort_by("doc_id")
        docs, keys = (np.asarray(t.column(c).to_numpy(), np.int64) for c in ("doc_id", "key"))
        w = Windows(b"\n".join(b" ".join(x.encode().split()) for x in t.column("text").to_pylist()), docs, window)
        known = w.repeats()
        ids, ks, data = _flag_rows(w.run[known], w.offset[known], docs, keys)
        where = [int(x) % buckets for x in ids]
        go = ~known
        run, offset, at, least = w.run[go], w.offset[go], w.at[go], w.minimisers()[go]
        if len(run):
            head = np.ones(len(run), bool)
            head[1:] = (run[1:] != run[:-1]) | (offset[1:] != offset[:-1] + 1) | (least[1:] != least[:-1])
            first = np.flatnonzero(head)
            many = np.diff(np.append(first, len(run)))
            bucket = (mix(least[first]) % np.uint64(buckets)).astype(np.int64)
            order = np.argsort(bucket, kind="stable")
            cut = np.append(np.flatnonzero(np.diff(bucket[order], prepend=-1)), len(order))
            for a, b in zip(cut[:-1], cut[1:], strict=True):
                own = first[order[a:b]]
                size = many[order[a:b]] + window - 1
                head_ = np.stack([docs[run[own]], keys[run[own]], offset[own], size], axis=1).astype("<i8")
                text = b"\n".join(w.text[x:y] for x, y in zip(w.start[at[own]].tolist(), w.end[at[own] + size - 1].tolist(), strict=True))
                ids.append(None)
                ks.append(len(head_))
                data.append(squeeze.compress(head_.tobytes() + text))
                where.append(int(bucket[order[a]]))
        yield pa.table([pa.array(where, pa.int32()), pa.array(ids, pa.int64()), pa.array(ks, pa.int64()), pa.array(data, pa.binary())], names=["bucket", "doc_id", "key", "data"])

    return kernel


def _resolver(window: int):
    def resolve(t: pa.Table) -> pa.Table:
        """One bucket: pass on what batches decided, decide the rest."""
        given, counts, data = t.column("doc_id").to_pylist(), t.column("key").to_pylist(), t.column("data").to_pylist()
        decided = [i for i, d in enumerate(given) if d is not None]
        out = [given[i] for i in decided], [counts[i] for i in decided], [data[i] for i in decided]
        heads, lines = [], []
        for d, n, blob in zip(given, counts, data, strict=True):
            if d is None:
                raw = zstandard.ZstdDecompressor().decompress(blob)
                heads.append(np.frombuffer(raw, "<i8", 4 * n).reshape(n, 4))
                lines += raw[32 * n :].split(b"\n")
        if heads:
            head = np.concatenate(heads)
            order = np.argsort(head[:, 0], kind="stable")
            head = head[order]
            w = Windows(b"\n".join(map(lines.__getitem__, order.tolist())), head[:, 0], window)
            known = w.repeats()
            run = w.run[known]
            for mine, more in zip(out, _flag_rows(run, head[run, 2] + w.offset[known], head[:, 0], head[:, 1]), strict=True):
                mine.extend(more)
        return pa.table([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.binary())], names=["doc_id", "key", "data"])

    return resolve


def repeated_windows(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """doc_id, key (32-bit hash of the text, which tells rows that repeat a doc_id apart), spans: for each document with repeated windows, packed int32 pairs (first window, how many).

    ``window`` is two words or more.
    """
    if window < 2:
        raise ValueError("a window has two words or more")
    spark = docs.sparkSession
    buckets = BUCKETS_A_PARTITION * int(spark.conf.get("spark.sql.shuffle.partitions"))
    keyed = slim(docs, "doc_id", "text").where("doc_id is not null and text is not null").select("doc_id", F.hash("text").cast("long").alias("key"), "text")
    sent = in_batches(keyed, _sender(window, buckets), "bucket int, doc_id long, key long, data binary")
    flags = sent.groupBy("bucket").applyInArrow(_resolver(window), "doc_id long, key long, data binary")
    return flags.groupBy("doc_id", "key").agg(F.collect_list("data").alias("spans"))


def _covered(n: int, spans: list[bytes] | None, window: int) -> np.ndarray:
    gone = np.zeros(n + 1, np.int32)
    for start, many in np.concatenate([np.frombuffer(s, np.int32).reshape(-1, 2) for s in spans or []]) if spans else ():
        gone[start] += 1
        gone[min(n, start + many + window - 1)] -= 1
    return np.cumsum(gone[:n]) > 0


def _with_spans(docs: DataFrame, window: int) -> DataFrame:
    spans = repeated_windows(docs, window).select(F.col("doc_id").alias("__d"), F.col("key").alias("__k"), F.col("spans").alias("__spans"))
    return docs.join(spans, (F.col("doc_id") == F.col("__d")) & (F.hash("text") == F.col("__k")), "left").drop("__d", "__k")


def substring_duplicates(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 (of the kept words joined by one space) for every row."""

    def kernel(t: pa.Table) -> Iterator[pa.Table]:
        rows = []
        for text, spans in zip(t.column("text").to_pylist(), t.column("__spans").to_pylist(), strict=True):
            words = (text or "").encode().split()
            gone = _covered(len(words), spans, window)
            kept = [w for w, g in zip(words, gone.tolist(), strict=True) if not g] if spans else words
            rows.append((len(words), len(words) - len(kept), hashlib.sha256(b" ".join(kept)).hexdigest()))
        n, removed, digest = zip(*rows, strict=True)
        yield pa.table([t.column("doc_id"), pa.array(n, pa.int64()), pa.array(removed, pa.int64()), pa.array(digest, pa.string())], names=["doc_id", "n_words", "n_removed", "kept_sha256"])

    return in_batches(_with_spans(slim(docs, "doc_id", "text"), window), kernel, "doc_id long, n_words long, n_removed long, kept_sha256 string")


def cut_text(text: str, spans: list[bytes], window: int = WINDOW) -> str:
    """The text without its repeated words; the white space before a kept word stays."""
    raw = text.encode()
    pieces = _PIECE.findall(raw)
    gone = _covered(len(pieces), spans, window).tolist()
    return b"".join(space + word for (space, word), g in zip(pieces, gone, strict=True) if not g).decode()


def without_repeats(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """``docs`` with repeated words cut from ``text`` and ``n_chars`` set anew; a document all of whose words go is dropped."""
    names = docs.columns
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)

    def kernel(t: pa.Table) -> Iterator[pa.Table]:
        texts, spans = t.column("text").to_pylist(), t.column("__spans").to_pylist()
        new = [cut_text(x, s, window) if s else x for x, s in zip(texts, spans, strict=True)]
        out = t.select(names).set_column(names.index("text"), "text", pa.array(new, pa.string()))
        if "n_chars" in names:
            was = t.column("n_chars").to_pylist()
            i = names.index("n_chars")
            out = out.set_column(i, "n_chars", pa.array([len(x) if s else w for x, s, w in zip(new, spans, was, strict=True)], t.schema.field("n_chars").type))
        yield out.filter(pa.array([not s or bool(x.strip()) for x, s in zip(new, spans, strict=True)], pa.bool_()))

    return in_batches(_with_spans(docs, window), kernel, fields)
