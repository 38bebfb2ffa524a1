import json
import random

import pytest


@pytest.fixture(scope="session")
def words():
    rng = random.Random(5)
    return ["".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(rng.randint(2, 9))) for _ in range(3000)]


@pytest.fixture(scope="session")
def docs_of(spark):
    """(doc_id, text[, lang]) rows to a documents table with columns whose names the operators use inside."""

    def make(rows):
        full = [(r[0], r[1], r[2] if len(r) > 2 else "en", "src", 0, "x", 1) for r in rows]
        return spark.createDataFrame(full, "doc_id long, text string, lang string, source string, n_chars long, key string, bucket int")

    return make


ODD = [(100, None), (101, ""), (102, " \t\n "), (103, "one"), (104, "Ünï ☃ 漢字"), (None, "no id at all here"), (105, "the the the the the the"), (105, "the the the the the the")]


@pytest.fixture(scope="session")
def odd():
    return list(ODD)


@pytest.fixture(scope="session")
def as_rows():
    return lambda df, *by: sorted((tuple(r) for r in df.collect()), key=lambda r: json.dumps(r, default=str))


def _run(marks):
    """The longest stretch by equal words that starts where the share before it fell below 0.6."""
    best, matched, overlap = (0, 0), 0, 0
    for m in marks:
        matched, overlap = matched + bool(m), overlap + 1
        if matched < 0.6 * overlap:
            matched = overlap = 0
        if matched > best[0]:
            best = matched, overlap
    return best


@pytest.fixture(scope="session")
def contaminates():
    """Does an item contaminate a text? The rule of op 3, pair by pair, without seeds as joins."""
    import regex

    from ergodica.llm import decontaminate as dc

    def words_of(text):
        return regex.findall(r"[\p{L}\p{N}]+", (text or "").lower())

    def judge(text, item_text):
        doc, item = words_of(text), words_of(item_text)
        n = len(item)
        if not n or n < dc.SPAN:
            return bool(n) and any(doc[i : i + n] == item for i in range(len(doc) - n + 1))
        if len(doc) < dc.SPAN:
            return False
        hits = set()
        for mask in dc.MASKS:
            at = {}
            for i in range(n - mask[-1]):
                at.setdefault(tuple(item[i + p] for p in mask), []).append(i)
            for i in range(len(doc) - mask[-1]):
                hits |= {i - j for j in at.get(tuple(doc[i + p] for p in mask), ())}
        groups = []
        for d in sorted(hits):
            if groups and d - groups[-1][-1] <= dc.REACH:
                groups[-1].append(d)
            else:
                groups.append([d])
        for lay in [[d] for d in hits] + [g for g in groups if len(g) > 1]:
            inside = [[0 <= i + d < len(doc) for d in lay] for i in range(n)]
            marks = [any(k and doc[i + d] == item[i] for d, k in zip(lay, inside[i], strict=True)) for i in range(n)]
            overlap = sum(any(k) for k in inside) if len(lay) == 1 else n
            if overlap >= max(dc.SPAN, 0.6 * n) and sum(marks) >= 0.6 * overlap:
                return True
            matched, length = max(_run(marks), _run(marks[::-1]))
            if length >= dc.SPAN and matched >= min(dc.RUN_WORDS, 0.6 * n):
                return True
        return False

    return judge
