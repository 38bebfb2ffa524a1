"""Tokenise documents and pack them into sequences by bounded-space online best-fit.

Each partition packs its own documents in one narrow pass: no shuffle, nothing gathered. Open bins are kept by their free
space; one Python integer is the bitset of the free spaces that have an open bin, so the tightest bin that takes a piece
is the lowest set bit at or above its length. At most ``open_bins`` bins are open; one more closes the fullest first.
The pieces of one Arrow slice (some ``SLICE`` bytes of text) arrive together and are placed longest first. A bin's pieces are held until
it closes; what lies in bins that still have ``SPARE`` of their space when a partition ends is packed again, the same way, by a small second pass.

Tokens: no token crosses white space in the tokenizer named by the contract, so a white-space chunk's ids are looked up
in a cache of at most ``CACHE`` chunks of at most ``LONGEST`` letters. Unseen chunks of Latin letters are split like the tokenizer does and merged many at a time (``bpe``); other
and longer chunks, and texts with the separators 0x1C to 0x1F, which only Python counts as white space, go to the tokenizer itself.

Defined results. Null or empty text: the one end id. Only documents longer than a sequence are cut; the last piece may be
shorter. Null doc_id and repeated rows: packed like any other row. Pieces of equal length: in the order of the rows. Extra columns are ignored. Empty table: no rows.
"""

from __future__ import annotations

import re
import unicodedata
import zlib
from collections.abc import Iterator
from itertools import accumulate, chain, islice

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bpe import Merges
from .common import give_back, slices, slim, written

SEQUENCE = 2048
OPEN_BINS = 1024
SPARE = 0.05
CACHE, LONGEST = 300_000, 64  # chunks a task remembers, letters of one: 130 MB at the worst
SLICE = 1 << 20
AT_ONCE = 16_384  # chunks learnt at a time
AGAIN = 50_000  # pieces of one task of the second pass
_ODD = re.compile("[\x1c-\x1f]")
_LATIN = [chr(c) for c in range(33, 0x180) if not chr(c).isspace()]
_LETTERS = re.escape("".join(c for c in _LATIN if unicodedata.category(c)[0] == "L"))
_NUMBERS = re.escape("".join(c for c in _LATIN if unicodedata.category(c)[0] == "N"))
_RARE = re.compile("[^\x20-\u012f\u0131-\u017f]|<\\|")  # beyond what the fast path splits: left to the tokenizer
_PIECES = re.compile(rf"\n|'s|'t|'re|'ve|'m|'ll|'d|[{_LETTERS}]+|[{_NUMBERS}]|[^\s{_LETTERS}{_NUMBERS}]+")


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class ChunkEncoder:
    """Text to the little-endian 32-bit ids of its tokens."""

    def __init__(self, path: str, cache: int = CACHE):
        from tokenizers import Tokenizer

        self.tokenizer, self.merges, self.limit, self.known = Tokenizer.from_file(path), Merges(path), cache, {}

    def _whole(self, text: str) -> bytes:
        return np.asarray(self.tokenizer.encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def _learn(self, chunks: list[str]) -> dict[str, bytes]:
        found: dict[str, bytes] = {}
        for a in range(0, len(chunks), AT_ONCE):
            some = chunks[a : a + AT_ONCE]
            rare = [c for c in some if len(c) > LONGEST or _RARE.search(c)] if _RARE.search(" ".join(some)) or max(map(len, some)) > LONGEST else []
            found.update((c, self._whole(c)) for c in rare)
            if plain := list(set(some).difference(rare)) if rare else some:
                self._merge(plain, found)
        return found

    def _merge(self, plain: list[str], found: dict[str, bytes]) -> None:
        pieces = _PIECES.findall("\n".join(plain).lower())
        distinct = list(set(pieces) - {"\n"})
        ids = dict(zip(distinct, self.merges.packed([p.encode() for p in distinct]), strict=True)) | {"\n": b"\xff" * 4}
        raw = b"".join(map(ids.__getitem__, pieces))
        cuts = (4 * np.flatnonzero(np.frombuffer(raw, "<u4") == 0xFFFFFFFF)).tolist()
        found.update((c, raw[a:b]) for c, a, b in zip(plain, [0, *(x + 4 for x in cuts)], [*cuts, len(raw)], strict=True))

    def encode(self, texts: list[str]) -> list[bytes]:
        odd = [bool(_ODD.search(t)) for t in texts]
        chunks = [[] if o else t.split() for t, o in zip(texts, odd, strict=True)]
        flat = list(chain.from_iterable(chunks))
        ids = list(map(self.known.get, flat))
        missing = [i for i, v in enumerate(ids) if v is None]
        fresh = self._learn(list({flat[i] for i in missing}))
        if len(self.known) + len(fresh) > self.limit:
            self.known = {c: v for c, v in zip(flat, ids, strict=True) if v is not None}  # what this batch uses stays
        for i in missing:
            ids[i] = fresh[flat[i]]
        room = max(0, self.limit - len(self.known))
        self.known.update(islice(((c, v) for c, v in fresh.items() if len(c) <= LONGEST), room))
        ends = list(accumulate(map(len, chunks)))
        return [self._whole(t) if o else b"".join(ids[a:b]) for t, o, a, b in zip(texts, odd, [0, *ends], ends, strict=False)]


_ENCODERS: dict[str, ChunkEncoder] = {}  # of this worker process: the tables are built once


def encoder(path: str) -> ChunkEncoder:
    if path not in _ENCODERS:
        _ENCODERS[path] = ChunkEncoder(path)
    return _ENCODERS[path]


class BestFit:
    """Bins of one size; ``place`` returns the bin's number and the offset in it, and adds to ``closed`` the bins that take nothing more."""

    def __init__(self, size: int, open_bins: int = OPEN_BINS):
        self.size, self.most = size, open_bins
        self.free: list[list[int]] = [[] for _ in range(size + 1)]
        self.closed: list[int] = []
        self.bits = self.open = self.made = 0

    def _take(self, free: int) -> int:
        found = self.free[free].pop()
        if not self.free[free]:
            self.bits &= ~(1 << free)
        self.open -= 1
        return found

    def place(self, length: int) -> tuple[int, int]:
        fits = self.bits >> length
        if fits:
            free = length + (fits & -fits).bit_length() - 1
            found = self._take(free)
        else:
            free, found = self.size, self.made
            self.made += 1
        if left := free - length:
            if self.open >= self.most:
                self.closed.append(self._take((self.bits & -self.bits).bit_length() - 1))  # the fullest closes
            self.free[left].append(found)
            self.bits |= 1 << left
            self.open += 1
        else:
            self.closed.append(found)
        return found, self.size - free

    def spare(self, least: int) -> set[int]:
        """Open bins with ``least`` or more of free space."""
        return {b for free in range(least, self.size + 1) for b in self.free[free]}


COLUMNS = ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]
SCHEMA = "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long"
_TYPES = [pa.int64(), pa.int32(), *[pa.int64()] * 5]


def _table(rows: list[list], with_ids: bool, closed: list[bool] | None) -> pa.RecordBatch:
    """Rows [the columns ..., ids as bytes] as a batch."""
    cols = list(zip(*rows, strict=True))
    arrays, names = [pa.array(c, k) for c, k in zip(cols, _TYPES, strict=False)], list(COLUMNS)
    if with_ids:
        flat = np.frombuffer(b"".join(cols[7]), "<i4")
        arrays.append(pa.ListArray.from_arrays(pa.array(np.cumsum([0, *cols[3]]), pa.int32()), pa.array(flat)))
        names.append("ids")
    if closed is not None:
        arrays.append(pa.array(closed, pa.bool_()))
        names.append("closed")
    return pa.RecordBatch.from_arrays(arrays, names=names)


def _fill(groups: Iterator[list[list]], bins: BestFit, base: int, with_ids: bool, spare: int | None) -> Iterator[pa.RecordBatch]:
    """Groups of rows [doc_id, piece, start, length, crc, 0, 0, ids] placed, each group longest first; a bin's rows leave when it closes.

    ``spare`` given: a column ``closed`` tells the rows of bins that have so much free space at the end from the others.
    """
    held: dict[int, list[list]] = {}
    for rows in groups:
        for r in sorted(rows, key=lambda r: -r[3]):
            number, r[6] = bins.place(r[3])
            r[5] = base + number
            held.setdefault(number, []).append(r)
        if out := [r for b in bins.closed for r in held.pop(b)]:
            yield _table(out, with_ids, None if spare is None else [True] * len(out))
        bins.closed.clear()
    again = bins.spare(spare) if spare is not None else set()
    numbers = list(held)
    for a in range(0, len(numbers), 128):
        out = [(r, b not in again) for b in numbers[a : a + 128] for r in held.pop(b)]
        yield _table([r for r, _ in out], with_ids, None if spare is None else [c for _, c in out])


def pack(docs: DataFrame, tokenizer: str, sequence: int = SEQUENCE, end_id: int = 0, open_bins: int = OPEN_BINS, with_ids: bool = False, spare: float = SPARE) -> DataFrame:
    """One row per piece; ``with_ids`` adds the piece's token ids."""
    end = np.asarray([end_id], "<u4").tobytes()
    schema = SCHEMA + ", ids array<int>" * with_ids

    def cut(batch: pa.RecordBatch, encode) -> list[list]:
        rows = []
        for doc, ids in zip(batch.column(0).to_pylist(), encode([x or "" for x in batch.column(1).to_pylist()]), strict=True):
            ids += end
            for piece, at in enumerate(range(0, len(ids), 4 * sequence)):
                part = ids[at : at + 4 * sequence]
                rows.append([doc, piece, at // 4, len(part) // 4, zlib.crc32(part), 0, 0, part if with_ids else None])
        return rows

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        maker = encoder(tokenizer)
        base = (TaskContext.get().partitionId() if TaskContext.get() else 0) << 32
        groups = (cut(part, maker.encode) for whole in batches for part in slices(whole, SLICE))
        try:
            yield from _fill(groups, BestFit(sequence, open_bins), base, with_ids, max(1, int(spare * sequence)))
        finally:
            maker.known = {}  # the worker lives on for other tasks
            give_back()

    def second(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        base = 1 << 62 | (TaskContext.get().partitionId() if TaskContext.get() else 0) << 32

        def rows(part: pa.RecordBatch) -> list[list]:
            cols = [part.column(c).to_pylist() for c in COLUMNS[:5]]
            ids = [x.values.to_numpy().astype("<i4").tobytes() for x in part.column("ids")] if with_ids else [None] * part.num_rows
            return [[*r[:5], 0, 0, r[5]] for r in zip(*cols, ids, strict=True)]

        yield from _fill((rows(part) for whole in batches for part in slices(whole, SLICE)), BestFit(sequence, open_bins), base, with_ids, None)
        give_back()

    placed = written(slim(docs, "doc_id", "text").mapInArrow(first, f"{schema}, closed boolean"), "packed")
    left = placed.where("not closed").drop("closed")
    tasks = -(-left.count() // AGAIN)
    if not tasks:
        return placed.drop("closed")
    return placed.where("closed").drop("closed").unionByName(left.repartition(tasks).sortWithinPartitions(F.desc("length")).mapInArrow(second, schema))
