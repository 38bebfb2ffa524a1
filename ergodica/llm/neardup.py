"""Near duplicates by SuperMinHash signatures, banding, verification on full shingle sets, and union-find grouping.

*Signature.* Every shingle draws a random permutation of the ``M`` registers step by step; at step j it offers the value
``j + r`` to the register the permutation names. A register keeps the least offer. Because the offers of one shingle are
spread over different registers, the signature's similarity estimate has a lower variance than independent hashes, and a
document stops as soon as all its registers hold values below the next step (usually two or three steps).

*Candidates.* 32 bands of 4 registers: a link of similarity 0.8 is missed with probability (1 - 0.8^4)^32 < 5e-8.

*Grouping.* Equal word sequences collapse to one representative. A band's documents are not paired with one another: each
is checked against one hub, confirmed links are grouped, and only bands whose documents still lie in different
components go on to the next round with other hubs. What is left after ``HUB_ROUNDS`` goes through an exact comparison of
every two documents of different components, in blocks of documents, so no link is lost and no pair list is made.

Defined results. Null or empty text, or text without words: an empty set, linked with nothing (its own component). Fewer
words than a shingle: the whole sequence is the one shingle. Null ``doc_id``: linked with nothing, component null, kept.
Rows that repeat a doc_id are one document. Extra columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import in_batches, joined_by_key, slim, written
from .components import components

REGISTERS, BANDS = 128, 32
HUB_ROUNDS = 2
HUB_PAIRS = 2048  # pairs of one hub that are checked in one place
BLOCK = 1024  # documents of one side of an exact block comparison
_GOLDEN = np.uint64(0x9E3779B97F4A7C15)


def mix(x: np.ndarray) -> np.ndarray:
    """The splitmix64 finaliser."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def words_of(text: str | None) -> list[bytes]:
    return (text or "").encode().lower().split()  # bytes.lower() is A-Z only


def shingle_set(words: list[bytes], n: int) -> set:
    """The exact set: distinct runs of n words; with fewer words the whole sequence; without words empty."""
    if len(words) <= n:
        return {tuple(words)} if words else set()
    return set(zip(*(words[i:] for i in range(n)), strict=False))


def hashed_shingles(docs: list[list[bytes]], n: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct 64-bit shingle hashes of each document, and the document of each."""
    lengths = np.fromiter(map(len, docs), np.int64, len(docs))
    w = np.fromiter(map(xxhash.xxh3_64_intdigest, chain.from_iterable(docs)), np.uint64, int(lengths.sum()))
    starts = np.cumsum(lengths) - lengths
    counts = np.where(lengths > 0, np.maximum(lengths - n + 1, 1), 0)
    owner = np.repeat(np.arange(len(docs)), counts)
    at = starts[owner] + np.arange(len(owner)) - np.repeat(np.cumsum(counts) - counts, counts)
    end = (starts + lengths)[owner]
    h = np.zeros(len(owner), np.uint64)
    for i in range(n):
        inside = at + i < end
        step = np.where(inside, w[np.minimum(at + i, max(0, len(w) - 1))] if len(w) else 0, np.uint64(i + 1))
        h = mix(h * np.uint64(3) + step + _GOLDEN)
    order = np.lexsort((h, owner))
    h, owner = h[order], owner[order]
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (owner[1:] != owner[:-1])
    return h[new], owner[new]


def superminhash(elements: np.ndarray, owner: np.ndarray, docs: int, m: int = REGISTERS) -> np.ndarray:
    """Signatures (docs, m) of int64 values; a value's high half is the step, its low half the random part."""
    far = np.iinfo(np.int64).max
    sig = np.full((docs, m), far, np.int64)
    flat = sig.reshape(-1)
    draws: list[np.ndarray] = []  # draws[i]: the place each live element swapped with at step i
    for j in range(m):
        if not len(elements):
            break
        z = mix(elements + np.array([j + 1], np.uint64) * _GOLDEN)
        k = j + (((z >> np.uint64(32)) * np.uint64(m - j)) >> np.uint64(32)).astype(np.int64)
        register = k.copy()
        for i in range(j - 1, -1, -1):  # what earlier swaps put there
            register[register == draws[i]] = i
        np.minimum.at(flat, owner * m + register, (np.int64(j) << 32) | (z & np.uint64(0xFFFFFFFF)).astype(np.int64))
        open_ = (sig.max(axis=1) >= np.int64(j + 1) << 32)[owner]
        draws = [d[open_] for d in [*draws, k]]
        elements, owner = elements[open_], owner[open_]
    return sig


def band_keys(sig: np.ndarray, bands: int = BANDS) -> np.ndarray:
    rows = sig.shape[1] // bands
    x = sig[:, : bands * rows].reshape(len(sig), bands, rows).astype(np.uint64)
    h = np.broadcast_to(np.arange(1, bands + 1, dtype=np.uint64) * _GOLDEN, x.shape[:2])
    for r in range(rows):
        h = mix(h * np.uint64(5) + x[:, :, r])
    return h.view(np.int64) if h.flags.c_contiguous else np.ascontiguousarray(h).view(np.int64)


def sketches(docs: DataFrame, n: int) -> DataFrame:
    """doc_id, n_shingles, print (digest of the word sequence; null without words), bands."""

    def kernel(t: pa.Table) -> Iterator[pa.Table]:
        words = [words_of(x) for x in t.column("text").to_pylist()]
        h, owner = hashed_shingles(words, n)
        keys = band_keys(superminhash(h, owner, len(words)))
        prints = [hashlib.blake2b(b" ".join(w), digest_size=16).digest() if w else None for w in words]
        bands = pa.ListArray.from_arrays(pa.array(np.arange(len(words) + 1, dtype=np.int32) * BANDS), pa.array(keys.reshape(-1)))
        yield pa.table([t.column("doc_id"), pa.array(np.bincount(owner, minlength=len(words)), pa.int64()), pa.array(prints, pa.binary()), bands], names=["doc_id", "n_shingles", "print", "bands"])

    return in_batches(slim(docs, "doc_id", "text"), kernel, "doc_id long, n_shingles long, print binary, bands array<long>")


def _similar(a: set, b: set, num: int, den: int) -> bool:
    if den * min(len(a), len(b)) < num * max(len(a), len(b)):
        return False
    both = len(a & b)
    return den * both >= num * (len(a) + len(b) - both)


def _confirmed(pairs: DataFrame, texts: DataFrame, n: int, num: int, den: int) -> DataFrame:
    """Of pairs (a, hub) those whose full sets are similar. A hub's pairs go to as many tasks as they have times ``HUB_PAIRS``, each with a copy of its
    text; sorted by hub within a task, its set is made once."""
    pairs = written(pairs, "pairs")
    many = pairs.groupBy("hub").agg(F.ceil(F.count("*") / HUB_PAIRS).cast("int").alias("salts"))
    hubs = texts.select(F.col("doc_id").alias("hub"), F.col("text").alias("hub_text")).join(many, "hub").withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("salts") - 1))).drop("salts")
    wide = written(many.where("salts > 1").withColumn("n", F.col("salts") * HUB_PAIRS), "wide")
    salted = joined_by_key(pairs, wide, "hub").withColumn("salt", F.pmod(F.xxhash64("a"), F.col("salts")).cast("int")).drop("salts")
    dealt = salted.unionByName(pairs.join(wide.select("hub"), "hub", "left_anti").withColumn("salt", F.lit(0)))
    with_text = dealt.join(texts.select(F.col("doc_id").alias("a"), "text"), "a").join(hubs, ["hub", "salt"])

    def kernel(t: pa.Table) -> Iterator[pa.Table]:
        sets: dict[str, set] = {}
        hub_text, yes = t.column("hub_text").to_pylist(), []
        for text, hub in zip(t.column("text").to_pylist(), hub_text, strict=True):
            if hub not in sets:
                sets.clear()
                sets[hub] = shingle_set(words_of(hub), n)
            yes.append(_similar(shingle_set(words_of(text), n), sets[hub], num, den))
        yield t.select(["a", "hub"]).rename_columns(["a", "b"]).filter(pa.array(yes, pa.bool_()))

    return in_batches(with_text.select("a", "hub", "text", "hub_text"), kernel, "a long, b long")


def _open(members: DataFrame, comp: DataFrame) -> DataFrame:
    """Members (doc_id, key) of bands whose documents still lie in more than one component, with their component."""
    now = written(members.join(comp.select(F.col("node").alias("doc_id"), "component"), "doc_id", "left").withColumn("component", F.coalesce("component", "doc_id")), "placed")
    mixed = now.groupBy("key").agg(F.min("component").alias("lo"), F.max("component").alias("hi"), F.count("*").alias("n")).where("lo < hi").select("key", "n")
    return joined_by_key(now, written(mixed, "mixed"), "key")


def _hashed_sets(texts: DataFrame, n: int) -> DataFrame:
    """doc_id, hashes: the full shingle set as packed 64-bit hashes."""

    def kernel(t: pa.Table) -> Iterator[pa.Table]:
        h, owner = hashed_shingles([words_of(x) for x in t.column("text").to_pylist()], n)
        ends = np.searchsorted(owner, np.arange(1, t.num_rows))
        yield pa.table([t.column("doc_id"), pa.array([x.tobytes() for x in np.split(h, ends)], pa.binary())], names=["doc_id", "hashes"])

    return in_batches(texts, kernel, "doc_id long, hashes binary")


def spanning_links(ids: np.ndarray, comp: np.ndarray, block: np.ndarray, sets: list[np.ndarray], num: int, den: int) -> list[tuple[int, int]]:
    """Links between components among all pairs of documents (of two blocks, or within one), from exact intersection sizes.

    Shared shingles are the columns of a 0/1 matrix; its products, taken over slices of columns, count them for all pairs at once.
    """
    size = np.fromiter(map(len, sets), np.int64, len(sets))
    _, column, many = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    row, shared = np.repeat(np.arange(len(sets)), size), many[column] > 1
    number = np.cumsum(many > 1) - 1
    row, column = row[shared], number[column[shared]]
    left = np.flatnonzero(block == block.min())
    right = left if block.min() == block.max() else np.flatnonzero(block == block.max())
    both = np.zeros((len(left), len(right)), np.float32)
    order = np.argsort(column, kind="stable")
    row, column = row[order], column[order]
    for a in range(0, int(column[-1]) + 1 if len(column) else 0, 4096):
        lo, hi = np.searchsorted(column, [a, a + 4096])
        m = np.zeros((len(sets), 4096), np.float32)
        m[row[lo:hi], column[lo:hi] - a] = 1
        both += m[left] @ m[right].T
    total = size[left][:, None] + size[right][None, :] - both
    near = (den * both >= num * total) & (comp[left][:, None] != comp[right][None, :])
    parent: dict[int, int] = {}

    def root(c: int) -> int:
        while parent.get(c, c) != c:
            c = parent[c]
        return c

    out = []
    for x, y in zip(*(side.tolist() for side in np.nonzero(near)), strict=True):
        a, b = root(int(comp[left[x]])), root(int(comp[right[y]]))
        if a != b:
            parent[max(a, b)] = min(a, b)
            out.append((int(ids[left[x]]), int(ids[right[y]])))
    return out


def _exact_rest(open_: DataFrame, texts: DataFrame, n: int, num: int, den: int) -> DataFrame:
    """Every two documents that share an open band and lie in different components, compared by the hashes of their full sets; callers confirm
    the few links that come out on the words.

    A band's documents are dealt into blocks of about ``BLOCK``; two blocks meet in one cell and are compared within it,
    so what travels are documents times blocks, never pairs, and what is held is two blocks.
    """
    sizes = open_.groupBy("key").agg(F.count("*").alias("n")).withColumn("blocks", F.ceil(F.col("n") / BLOCK).cast("int"))
    dealt = joined_by_key(open_, written(sizes, "sizes"), "key").withColumn("block", F.pmod(F.xxhash64("doc_id", F.lit(3)), F.col("blocks")).cast("int"))
    meet = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other")
    cells = dealt.select("key", "doc_id", "component", "block", meet).select(
        "key", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "doc_id", "component", "block"
    )
    sets = _hashed_sets(texts.join(open_.select("doc_id").distinct(), "doc_id", "left_semi"), n)
    dealt_out = cells.join(sets, "doc_id").repartition("key", "i", "j").sortWithinPartitions("key", "i", "j")

    def compare(parts: list[pa.Table]) -> list[tuple[int, int]]:
        t = pa.concat_tables(parts)
        ids, comp, block = (t.column(c).to_numpy() for c in ("doc_id", "component", "block"))
        if comp.min() == comp.max():
            return []
        return spanning_links(ids, comp, block, [np.frombuffer(x, np.uint64) for x in t.column("hashes").to_pylist()], num, den)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, cell = [], None
        for batch in batches:
            found: list[tuple[int, int]] = []
            t = pa.Table.from_batches([batch])
            where = np.stack([t.column(c).to_numpy().astype(np.int64) for c in ("key", "i", "j")], axis=1)
            cuts = [0, *(np.flatnonzero((where[1:] != where[:-1]).any(axis=1)) + 1).tolist(), len(where)]
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                if a == b:
                    continue
                if held and tuple(where[a]) != cell:
                    found += compare(held)
                    held = []
                held.append(t.slice(a, b - a))
                cell = tuple(where[a])
            yield _link_batch(found)
        if held:
            yield _link_batch(compare(held))

    return dealt_out.mapInArrow(run, "a long, b long")


def _link_batch(links: list[tuple[int, int]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([x[i] for x in links], pa.int64()) for i in (0, 1)], names=["a", "b"])


def near_duplicates(docs: DataFrame, words: int = 5, similarity: tuple[int, int] = (4, 5)) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every row of ``docs``: components of documents whose sets have a Jaccard similarity of num/den or more."""
    num, den = similarity
    marked = written(sketches(docs, words), "sketches")
    real = marked.where(F.col("doc_id").isNotNull() & F.col("print").isNotNull())
    groups = written(real.groupBy("print").agg(F.min("doc_id").alias("rep")), "prints")
    reps = real.join(groups, (real["print"] == groups["print"]) & (real["doc_id"] == groups["rep"]), "left_semi")
    keys = written(reps.select("doc_id", "bands"), "reps").select("doc_id", F.explode("bands").alias("key"))
    shared = keys.groupBy("key").agg(F.min("doc_id").alias("hub"), F.max("doc_id").alias("last"), F.count("*").alias("n")).where("hub < last").select("key", "hub", "n")
    members = written(joined_by_key(keys, written(shared, "shared"), "key"), "members")
    candidates = members.select("doc_id").distinct()
    texts = written(slim(docs, "doc_id", "text").join(candidates, "doc_id", "left_semi"), "texts")

    pairs = members.where("doc_id <> hub").select(F.col("doc_id").alias("a"), "hub").distinct()
    links = written(_confirmed(pairs, texts, words, num, den), "confirmed")
    comp = components(links)
    members = members.select("doc_id", "key")
    for turn in range(HUB_ROUNDS):
        members_open = written(_open(members, comp), "open")
        if members_open.isEmpty():
            break
        if turn == HUB_ROUNDS - 1:
            more = _confirmed(_exact_rest(members_open, texts, words, num, den).select("a", F.col("b").alias("hub")), texts, words, num, den)
        else:
            hub = F.min_by(F.struct("doc_id", "component"), F.xxhash64("doc_id", "key", F.lit(turn)))
            hubs = written(members_open.groupBy("key").agg(hub.alias("h"), F.count("*").alias("n")), "hubs")
            with_hub = joined_by_key(members_open, hubs, "key")
            pairs = with_hub.where(F.col("h.component") != F.col("component")).select(F.col("doc_id").alias("a"), F.col("h.doc_id").alias("hub")).distinct()
            more = _confirmed(pairs, texts, words, num, den)
        links = written(links.unionByName(more), "confirmed")
        comp = components(links)
        members = members_open.select("doc_id", "key")

    named = marked.select("doc_id", "n_shingles", "print").join(groups, "print", "left").join(comp.select(F.col("node").alias("rep"), "component"), "rep", "left")
    return named.select("doc_id", "n_shingles", F.coalesce("component", "rep", "doc_id").alias("component_id")).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def keep_one(docs: DataFrame, words: int = 5, similarity: tuple[int, int] = (4, 5)) -> DataFrame:
    """The rows of ``docs`` that stay: of each component the document with the least id."""
    gone = near_duplicates(docs, words, similarity).where(~F.col("kept")).select(F.col("doc_id").alias("__gone")).distinct()
    return docs.join(gone, docs["doc_id"] == gone["__gone"], "left_anti")
