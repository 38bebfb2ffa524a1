"""License scans: exact phrases, and fuzzy search of short notices.

*Fuzzy search.* A notice of n bytes may differ in up to ``n // ERROR_SHARE`` insertions, deletions and substitutions. Cut into
one piece more than that, at least one piece is unharmed (pigeonhole), so every match holds an exact seed. Seeds are
located by substring search; around each the regex library's bounded-error matching verifies the notice and gives its
span and errors. One narrow pass, no shuffle.

The text is searched as its words joined by single spaces: A-Z lower-cased, a word being a run of digits, a-z and
non-ASCII characters.

Defined results. Null or empty text: no words, no labels, null positions, score 0. Rows are judged one by one, whatever
their ids; extra columns are ignored.
"""

from __future__ import annotations

from bisect import bisect_right
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import in_batches, slim

# The contract's phrases.
PHRASES = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}
# Short notices of common licences, as words, and their labels.
NOTICES = {
    "permission is hereby granted free of charge": "mit",
    "released under the mit license": "mit",
    "licensed under the apache license version 2 0": "apache",
    "redistribution and use in source and binary forms": "bsd",
    "this program is free software you can redistribute it": "gpl",
    "under the terms of the gnu general public license": "gpl",
    "subject to the terms of the mozilla public license": "mpl",
    "creative commons attribution sharealike": "cc-by-sa",
    "creative commons attribution": "cc-by",
    "licensed under cc by": "cc-by",
    "released into the public domain": "public-domain",
    "all rights reserved": "reserved",
}
ERROR_SHARE = 10

_FOLD = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))


class Notice:
    def __init__(self, text: str, label: str):
        import regex

        self.text, self.label = text.encode(), label
        self.errors = len(self.text) // ERROR_SHARE
        n, k = len(self.text), self.errors + 1
        cuts = [i * n // k for i in range(k + 1)]
        self.seeds = [(self.text[a:b], a) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]
        self.pattern = regex.compile(b"(?e)(?:" + regex.escape(self.text, special_only=True) + b"){e<=%d}" % self.errors)

    def find(self, text: bytes) -> list[tuple[int, int, int]]:
        """(start, end, errors) of the matches in a normalised text, without overlaps."""
        windows: list[list[int]] = []
        for seed, at in self.seeds:
            i = text.find(seed)
            while i >= 0:
                windows.append([max(0, i - at - self.errors), i - at + len(self.text) + self.errors])
                i = text.find(seed, i + 1)
        if not windows:
            return []
        windows.sort()
        merged = [windows[0]]
        for w in windows[1:]:
            if w[0] <= merged[-1][1]:
                merged[-1][1] = max(merged[-1][1], w[1])
            else:
                merged.append(w)
        return [(a + m.start(), a + m.end(), sum(m.fuzzy_counts)) for a, b in merged for m in self.pattern.finditer(text[a:b])]


def normalised(text: str | None) -> tuple[bytes, int]:
    """Words joined by single spaces, with one space at each end; their number."""
    words = (text or "").encode().translate(_FOLD).split()
    return b" " + b" ".join(words) + b" ", len(words)


def places(text: bytes, phrase: bytes) -> list[int]:
    """Word positions where the phrase's words stand consecutively."""
    found, key = [], b" " + phrase + b" "
    i = text.find(key)
    seen = counted = 0
    while i >= 0:
        counted += text.count(b" ", seen, i)
        seen = i
        found.append(counted)
        i = text.find(key, i + 1)
    return found


def scan(docs: DataFrame, notices: dict[str, str] = NOTICES, phrases: dict[str, str] = PHRASES) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, spans (label, first_word, last_word, errors)."""
    fields = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, spans array<struct<label:string,first_word:long,last_word:long,errors:int>>"
    span = pa.list_(pa.struct([("label", pa.string()), ("first_word", pa.int64()), ("last_word", pa.int64()), ("errors", pa.int32())]))

    def kernel(t: pa.Table) -> Iterator[pa.Table]:
        wanted = [Notice(k, v) for k, v in notices.items()]
        exact = [(k.encode(), v, len(k.split())) for k, v in phrases.items()]
        rows = []
        for raw in t.column("text").to_pylist():
            text, n = normalised(raw)
            base = [(label, at, at + size - 1, 0) for phrase, label, size in exact for at in places(text, phrase)]
            more, score = [], 1.0 if base else 0.0
            for notice in wanted:
                if found := notice.find(text):
                    gaps = [i for i, c in enumerate(text) if c == 32]
                    for a, b, errors in found:
                        more.append((notice.label, max(0, bisect_right(gaps, a) - 1), max(0, min(n - 1, bisect_right(gaps, b - 1) - 1)), errors))
                        score = max(score, 1.0 - errors / len(notice.text))
            at = [x[1] for x in base]
            own = {x[0] for x in base}
            rows.append((n, len(base), min(at, default=None), max(at, default=None), ",".join(sorted(own)), ",".join(sorted(own | {x[0] for x in more})), score, sorted(base + more, key=lambda x: (x[1], x[2], x[0]))))
        cols = list(zip(*rows, strict=True))
        kinds = [pa.int64()] * 4 + [pa.string()] * 2 + [pa.float64(), span]
        spans = [[dict(zip(("label", "first_word", "last_word", "errors"), s, strict=True)) for s in r] for r in cols[7]]
        yield pa.table([t.column("doc_id"), *(pa.array(c, k) for c, k in zip([*cols[:7], spans], kinds, strict=True))], names=["doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", "spans"])

    return in_batches(slim(docs, "doc_id", "text"), kernel, fields)
