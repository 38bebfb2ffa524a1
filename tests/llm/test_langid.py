import zlib

import numpy as np

from ergodica.llm import langid


def test_gradient_is_the_derivative():
    m = langid.ByteTagger(["a", "b"], hidden=3, seed=1)
    for k in m.w:
        m.w[k] = m.w[k].astype(np.float64)
    rng = np.random.default_rng(0)
    ids, y = rng.integers(0, 257, (6, 4)).astype(np.int16), np.array([0, 1, 1, 0])
    loss, grad = m.gradients(ids, y)
    for k, at in (("gate_f", (0, 1)), ("cand_b", (1, 2)), ("out", (2, 1)), ("in_f", (int(ids[2, 1]), 4)), ("bias", (0,))):
        eps, old = 1e-3, m.w[k][at]
        m.w[k][at] = old + eps
        up = m.gradients(ids, y)[0]
        m.w[k][at] = old - eps
        down = m.gradients(ids, y)[0]
        m.w[k][at] = old
        assert abs((up - down) / (2 * eps) - grad[k][at]) < 2e-3 * max(1, abs(grad[k][at]))


def test_held_out_accuracy_and_rows(spark, sf2):
    docs = spark.read.parquet(f"{sf2}/documents.parquet")
    model = langid.train(docs, 500)
    got = langid.identify(docs, model).join(docs.select("doc_id", "lang"), "doc_id").toPandas()
    assert len(got) == docs.count() and got.score.between(0, 1).all()
    assert (got.held_out == [zlib.crc32(str(i).encode()) % 5 == 0 for i in got.doc_id]).all()
    held = got[got.held_out]
    assert (held.lang_pred == held.lang).mean() > 0.95
    assert langid.filter_languages(docs, model, least=0.3).count() >= 0.99 * docs.count()


def test_odd_rows(spark, docs_of, odd):
    docs = docs_of([*odd, (106, "12 34 !?")])
    tagger = langid.ByteTagger(["de", "en"])
    got = {r.doc_id: r for r in langid.identify(docs, tagger).collect()}
    assert all(got[i].lang_pred == "und" and got[i].score == 0 for i in (100, 101, 102, 106)) and got[104].lang_pred in ("de", "en")
    assert langid.identify(docs, tagger).count() == docs.count() and got[None].held_out is None
    assert langid.identify(docs, None).where("lang_pred <> 'und'").isEmpty()
    assert langid.train(docs.where("false")) is None and langid.identify(docs.where("false"), tagger).isEmpty()
    kept = langid.filter_languages(docs, tagger, least=0.0)
    assert kept.columns == docs.columns and 100 not in [r.doc_id for r in kept.collect()]
    assert langid.filter_languages(docs, tagger, ["xx"]).isEmpty()


def test_padding_does_not_count():
    m = langid.ByteTagger(["a", "b"])
    p = m.pooled([b"abc", b"", b"abc" * 100])
    assert np.allclose(p[0].sum(), 1, atol=1e-5) and p[1].sum() == 0 and np.allclose(p[2].sum(), 1, atol=1e-5)


def test_pooled_is_the_mean_over_bytes():
    """Every byte labelled by plain loops over one unit after the other."""
    import math

    m = langid.ByteTagger(["a", "b", "c"], hidden=3, seed=2)
    sig = lambda x: 1 / (1 + math.exp(-x))

    def states(side, ids):
        h, out = [0.0] * 3, {}
        for t in range(len(ids)) if side == "f" else reversed(range(len(ids))):
            x = m.w[f"in_{side}"][ids[t]]
            g = [sig(x[k] + sum(h[j] * m.w[f"gate_{side}"][j, k] for j in range(3))) for k in range(6)]
            c = [math.tanh(x[6 + k] + sum(g[j] * h[j] * m.w[f"cand_{side}"][j, k] for j in range(3))) for k in range(3)]
            h = out[t] = [c[k] + g[3 + k] * (h[k] - c[k]) for k in range(3)]
        return out

    texts = [b"short", bytes(range(65, 130)) * 3, b"", b"x" * langid.SEGMENT]
    got = m.pooled(texts, rows=2)
    for text, p in zip(texts, got, strict=True):
        total = [0.0] * 3
        for a in range(0, len(text), langid.SEGMENT):
            ids = list(text[a : a + langid.SEGMENT])
            pad = ids + [256] * (langid.SEGMENT - len(ids))  # the last segment is read with its padding
            f, b = states("f", pad), states("b", pad)
            for t in range(len(ids)):
                z = [m.w["bias"][k] + sum(v * m.w["out"][j, k] for j, v in enumerate(f[t] + b[t])) for k in range(3)]
                e = [math.exp(v) for v in z]
                total = [u + v / sum(e) for u, v in zip(total, e, strict=True)]
        assert all(abs(u / max(1, len(text)) - v) < 1e-5 for u, v in zip(total, p, strict=True))
