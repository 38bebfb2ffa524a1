import numpy as np

from ergodica.llm import ordinal as od


def test_thresholds_and_tails_are_ordered(spark, sf2):
    docs, labels = spark.read.parquet(f"{sf2}/documents.parquet"), spark.read.parquet(f"{sf2}/labels.parquet")
    model = od.train(docs, od.grades(labels))
    assert model.thresholds[0] < model.thresholds[1]
    tails = model.tails(np.linspace(-5, 5, 9))
    assert (tails[:, 0] >= tails[:, 1]).all() and (np.diff(tails[:, 0]) > 0).all()


def test_held_out_toxic(spark, sf2):
    import duckdb

    rows = duckdb.sql("select text, quality, toxic from '/root/testdata/sf0.1/documents.parquet' join '/root/testdata/sf0.1/labels.parquet' using (doc_id) order by doc_id").fetchall()
    y = np.array([0 if t else 2 if q else 1 for _, q, t in rows])
    held = np.arange(len(rows)) % 4 == 0
    m = od.CumulativeLink(3).fit([r[0] for r, h in zip(rows, held, strict=True) if not h], y[~held])
    p = m.tails(np.array([m.latent(*od.features(r[0])) for r, h in zip(rows, held, strict=True) if h]))[:, 0]
    assert (p[y[held] == 0] < 0.93).mean() > 0.9 and (p[y[held] == 2] < 0.93).mean() < 0.02


def test_gradient_lowers_the_loss():
    texts, y = ["bad words here"] * 40 + ["plain words here"] * 40 + ["fine words here"] * 40, np.repeat([0, 1, 2], 40)
    m = od.CumulativeLink(3).fit(texts, y)
    z = [m.latent(*od.features(t)) for t in ("bad words here", "plain words here", "fine words here")]
    assert z[0] < z[1] < z[2]


def test_slopes_are_finite_differences():
    m = od.CumulativeLink(4)
    m.base, m.steps = -0.7, np.array([0.1, -0.4])
    for grade in range(4):
        for z in (-1.3, 0.2, 2.0):
            _, d_z, d_t = m.slopes(grade, z)
            assert abs((m.slopes(grade, z + 1e-6)[0] - m.slopes(grade, z - 1e-6)[0]) / 2e-6 - d_z) < 1e-6
            by_base = []
            for e in (1e-6, -1e-6):
                n = od.CumulativeLink(4)
                n.base, n.steps = m.base + e, m.steps
                by_base.append(n.slopes(grade, z)[0])
            assert abs((by_base[0] - by_base[1]) / 2e-6 - d_t.sum()) < 1e-6


def test_score_is_the_formula(spark, docs_of, words):
    """Expected grade and tail by the definition, word by word, for every row."""
    import math

    import xxhash

    rows = [(i, " ".join(words[i : 7 * i])) for i in range(1, 12)] + [(50, "word. Word, #tag 12\n" * 30_000)]
    model = od.CumulativeLink(3).fit([t for _, t in rows], np.arange(len(rows)) % 3, epochs=3)
    got = {r.doc_id: r for r in od.score(docs_of(rows), model, least=0.4).collect()}
    for i, text in rows:
        parts: dict[int, float] = {}
        found = text.lower().split()
        for w in found:
            bare = w.strip(".,;:!?\"'()[]*#$%&|<>")
            for part in {bare, bare[:4] + "^", bare[:6] + "^"}:
                k = xxhash.xxh3_64_intdigest(part) % (1 << od.BITS)
                parts[k] = parts.get(k, 0) + 1
        n = len(text.encode())
        shares = [min(1, 5 * sum(text.count(c) for c in "#*$%&|<>@^~_=+\\/") / n), min(1, 5 * sum(c.isdigit() for c in text) / n), len(set(found)) / len(found), min(1, len(found) / 50), min(3, text.count("\n") / len(found) * 10), min(2, n / len(found) / 10)]
        z = sum(float(model.words[k]) * 6 * math.sqrt(c / len(found)) for k, c in parts.items()) + float(model.shares @ np.array(shares))
        tails = [1 / (1 + math.exp(t - z)) for t in model.thresholds]
        assert abs(got[i].tail - tails[0]) < 1e-4 and abs(got[i].expected_grade - sum(tails)) < 2e-4 and got[i].kept == (got[i].tail >= 0.4)


def test_odd_rows(spark, docs_of, odd):
    docs = docs_of([*odd, (1, "good text"), (2, "bad text")])
    labels = spark.createDataFrame([(1, 1, 0), (2, 0, 1), (2, 1, 0), (None, 1, 0), (3, None, None), (999, 1, 0)], "doc_id long, quality int, toxic int")
    g = {r.doc_id: r.grade for r in od.grades(labels).collect()}
    assert g == {1: 2, 2: 0, 999: 2}
    got = {r.doc_id: r for r in od.score(docs, od.train(docs, od.grades(labels))).collect()}
    assert got[100].tail == 0 and not got[101].kept
    plain = {r.doc_id: r for r in od.score(docs, None).collect()}
    assert plain[1].kept and plain[104].kept and not plain[100].kept and abs(plain[1].tail - 2 / 3) < 1e-12
    assert od.score(docs, None).count() == docs.count() and od.train(docs, od.grades(labels.where("false"))) is None
    assert od.score(docs.where("false"), None).isEmpty()
