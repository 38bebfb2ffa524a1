"""Byte-pair merges of many words at once: each round merges, in every word, its leftmost pair of least rank.

Merge lists give a pair a higher rank than the merges that made its parts, so one merge a round and word ends where a
priority queue does. A pair's rank is found by hashed tables (two or three levels) instead of per-word Python.
"""

from __future__ import annotations

import json
from itertools import chain

import numpy as np

FAR = np.int32(2**31 - 1)


def byte_letters() -> list[str]:
    """The printable letter that byte-level vocabularies use for each byte."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(rest)) for b in range(256)]


class Merges:
    def __init__(self, path: str, end: str = "</w>"):
        with open(path, encoding="utf-8") as f:
            model = json.load(f)["model"]
        vocab = model["vocab"]
        letters = byte_letters()
        self.inner = np.array([vocab[c] for c in letters], np.int64)
        self.last = np.array([vocab[c + end] for c in letters], np.int64)
        pairs = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in model["merges"]]
        keys = np.array([vocab[a] << 20 | vocab[b] for a, b in pairs], np.int64)
        into = np.array([vocab[a + b] for a, b in pairs], np.int32)
        self.levels = []
        left, turn = np.arange(len(keys)), 0
        while len(left):
            slot = self._slot(keys[left], turn)
            _, first = np.unique(slot, return_index=True)
            table = np.full(1 << 20, -1, np.int32)
            table[slot[first]] = left[first]
            self.levels.append(table)
            left, turn = np.delete(left, first), turn + 1
        self.keys, self.into = keys, into

    @staticmethod
    def _slot(keys: np.ndarray, turn: int) -> np.ndarray:
        return ((keys.astype(np.uint64) * np.uint64((0x9E3779B97F4A7C15, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F)[turn % 3] + 2 * (turn // 3))) >> np.uint64(44)).astype(np.int64)

    def ranks(self, keys: np.ndarray) -> np.ndarray:
        out = np.full(len(keys), FAR, np.int32)
        for turn, table in enumerate(self.levels):
            at = table[self._slot(keys, turn)]
            hit = (at >= 0) & (self.keys[at] == keys)
            out[hit] = at[hit]
        return out

    def encode(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all words one after the other, number of ids of each); no word is empty."""
        sizes = np.fromiter(map(len, words), np.int64, len(words))
        raw = np.frombuffer(b"".join(words), np.uint8)
        symbol, word = self.inner[raw], np.repeat(np.arange(len(words)), sizes)
        ends = np.cumsum(sizes) - 1
        symbol[ends] = self.last[raw[ends]]
        done_symbols, done_words = [], []
        while len(symbol):
            rank = np.full(len(symbol), FAR, np.int32)
            rank[:-1] = self.ranks(symbol[:-1] << 20 | symbol[1:])
            head = np.ones(len(word), bool)
            head[1:] = word[1:] != word[:-1]
            rank[:-1][head[1:]] = FAR  # no pair across words
            starts = np.flatnonzero(head)
            best = np.minimum.reduceat(rank, starts)
            open_ = best != FAR
            counts = np.diff(np.append(starts, len(word)))
            stays = np.repeat(open_, counts)
            done_symbols.append(symbol[~stays])
            done_words.append(word[~stays])
            at = np.flatnonzero((rank == np.repeat(best, counts)) & stays)
            if not len(at):
                break
            at = at[np.concatenate([[True], word[at][1:] != word[at][:-1]])]
            symbol[at] = self.into[rank[at]]
            stays[at + 1] = False
            symbol, word = symbol[stays], word[stays]
        symbols, owner = np.concatenate(done_symbols or [symbol]), np.concatenate(done_words or [word])
        return symbols[np.argsort(owner, kind="stable")].astype("<u4"), np.bincount(owner, minlength=len(words))

    def packed(self, words: list[bytes]) -> list[bytes]:
        """The little-endian ids of each word."""
        if not words:
            return []
        ids, counts = self.encode(words)
        raw, ends = ids.tobytes(), (4 * np.cumsum(counts)).tolist()
        return [raw[a:b] for a, b in zip(chain([0], ends[:-1]), ends, strict=True)]
