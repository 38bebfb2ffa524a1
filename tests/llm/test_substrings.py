import hashlib
import random

from ergodica.llm import substrings as ss


def brute(rows, window):
    first = {}
    split = lambda t: (t or "").encode().split()
    for d, t in rows:
        w = split(t)
        for i in range(len(w) - window + 1):
            if d is not None:
                k = tuple(w[i : i + window])
                first[k] = min(d, first.get(k, d))
    out = []
    for d, t in rows:
        w = split(t)
        gone = [False] * len(w)
        for i in range(len(w) - window + 1):
            if d is not None and first[tuple(w[i : i + window])] < d:
                gone[i : i + window] = [True] * window
        kept = [x for x, g in zip(w, gone, strict=True) if not g]
        out.append((d, len(w), sum(gone), hashlib.sha256(b" ".join(kept)).hexdigest()))
    return sorted(out, key=str)


def make(words):
    rng = random.Random(7)
    passages = [" ".join(rng.choice(words) for _ in range(rng.randint(13, 60))) for _ in range(5)]
    rows = []
    for d in range(60):
        parts = [" ".join(rng.choice(words[:40] if rng.random() < 0.3 else words) for _ in range(rng.randint(0, 40))) for _ in range(3)]
        if rng.random() < 0.7:
            parts.insert(rng.randrange(3), rng.choice(passages))
        rows.append((d, rng.choice([" ", "\n", "\t "]).join(parts)))
    rows += [(61, rows[3][1]), (62, rows[3][1]), (63, "same " * 50), (64, "same " * 30), (65, "x" * 9000 + " " + passages[0])]
    return rows


def test_equals_brute_force(spark, docs_of, words, odd, monkeypatch):
    rows = make(words) + odd
    for chunk in (64, 1 << 20):
        monkeypatch.setattr(ss, "CHUNK", chunk)
        got = ss.substring_duplicates(docs_of(rows)).collect()
        assert sorted((tuple(r) for r in got), key=str) == brute(rows, 13)
    got = ss.substring_duplicates(docs_of(rows).repartition(7), 3).collect()
    assert sorted((tuple(r) for r in got), key=str) == brute(rows, 3)


def test_hash_collisions_are_resolved(monkeypatch):
    import numpy as np

    runs, docs = [b"a b c d", b"b c d e", b"a b c x"], np.array([0, 1, 2])
    w = ss.Windows(b"\n".join(runs), docs, 3)
    w.hashes = np.zeros_like(w.hashes)  # every word alike
    assert w.repeats().tolist() == [False, False, True, False, True, False]


def test_texts_are_cut_in_place(spark, docs_of, words, odd):
    passage = " ".join(words[:20])
    rows = [(1, f"start {passage} end"), (2, f"Other\n{passage}\n\nrest  of it"), (3, passage), *odd]
    docs = docs_of(rows)
    got = {r.doc_id: r for r in ss.without_repeats(docs).collect()}
    assert got[1].text == rows[0][1] and got[2].text == "Other\n\nrest  of it" and 3 not in got
    assert got[2].n_chars == len(got[2].text) and got[1].n_chars == 0 and got[100].text is None and got[101].text == ""
    assert ss.without_repeats(docs).columns == docs.columns
    assert ss.substring_duplicates(docs.where("false")).isEmpty()
