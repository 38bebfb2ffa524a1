import re

from ergodica.llm import licenses as lc


def base(text):
    t = re.sub("[A-Z]", lambda m: m[0].lower(), text or "")
    w = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", t)
    at = [(i, label) for p, label in lc.PHRASES.items() for i in range(len(w)) if w[i : i + len(p.split())] == p.split()]
    return len(w), len(at), min((i for i, _ in at), default=None), max((i for i, _ in at), default=None), ",".join(sorted({label for _, label in at}))


def test_base_and_fuzzy(spark, docs_of, odd):
    rows = [
        (1, "x CC-BY y cc by cc by"), (2, "Under the GNU General Public License. All rights reserved"), (3, "cc bye, general public licenses"), (4, "cc  BY"),
        (5, "Permision is hereby granted, free of chrge to you"), (6, "all rigths reservd"), (7, "this text permits nothing of the kind"), *odd,
    ]
    got = {r.doc_id: r for r in lc.scan(docs_of(rows)).collect()}
    for d, t in rows:
        r = got[d]
        assert (r.n_words, r.n_base, r.first_word, r.last_word, r.base_labels) == base(t), d
        assert set(filter(None, r.base_labels.split(","))) <= set(filter(None, r.labels.split(","))) and 0 <= r.score <= 1
    assert got[5].labels == "mit" and got[5].base_labels == "" and 0.8 < got[5].score < 1
    assert [s.label for s in got[5].spans] == ["mit"] and (got[5].spans[0].first_word, got[5].spans[0].last_word) == (0, 6) and got[5].spans[0].errors == 2
    assert got[7].labels == "" and got[7].score == 0 and got[6].labels == ""
    assert lc.scan(docs_of(rows).where("false")).isEmpty()


def test_pigeonhole_misses_nothing():
    import random

    import regex

    rng = random.Random(3)
    n = lc.Notice("released into the public domain", "pd")
    for _ in range(300):
        t = list(n.text)
        for _ in range(rng.randint(0, n.errors)):
            i, kind = rng.randrange(len(t)), rng.randrange(3)
            t[i : i + 1] = [[rng.choice(b"abc ")], [], [t[i], rng.choice(b"abc ")]][kind]
        text = b" some words " + bytes(t) + b" and more "
        assert n.find(text) and regex.search(n.pattern, text)


def test_real_documents_equal_base(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    got = {r.doc_id: tuple(r)[1:6] for r in lc.scan(docs).collect()}
    assert all(got[r.doc_id] == base(r.text) for r in docs.collect())
