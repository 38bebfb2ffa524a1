import random
import zlib

import numpy as np
import pytest

from ergodica.llm import packing as pk


@pytest.fixture(scope="module")
def tokenizer():
    pytest.importorskip("public_tokenizers")
    from tokenizers import Tokenizer

    return Tokenizer.from_file(pk.tokenizer_path())


def test_ids_equal_the_tokenizers(tokenizer, words, sf):
    import duckdb

    rng = random.Random(1)
    texts = [r[0] for r in duckdb.sql(f"select text from '{sf}/documents.parquet'").fetchall()]
    texts += ["", " ", "a\x1cb", "İstanbul Σας", "it's we'll 'tis 12³½ ªº!?", "<|endoftext|>x y", "漢字 é", " nbsp x", "".join(chr(rng.randrange(33, 0x250)) for _ in range(500))]
    got = pk.ChunkEncoder(pk.tokenizer_path(), cache=50).encode(texts)
    assert got == [np.asarray(tokenizer.encode(t, add_special_tokens=False).ids, "<u4").tobytes() for t in texts]


def test_pieces(spark, docs_of, tokenizer, words, odd):
    rows = [(i, " ".join(words[: 40 * i])) for i in range(30)] + odd
    got = pk.pack(docs_of(rows), pk.tokenizer_path(), 256, with_ids=True).collect()
    by_doc, bins = {}, {}
    for r in got:
        by_doc.setdefault(r.doc_id, []).append(r)
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
        assert zlib.crc32(np.asarray(r.ids, "<u4").tobytes()) == r.ids_crc32 and len(r.ids) == r.length
    for d, t in rows[:30]:
        parts = sorted(by_doc[d], key=lambda r: r.piece)
        assert [x for p in parts for x in p.ids] == [*tokenizer.encode(t, add_special_tokens=False).ids, 0]
        assert all(p.length == 256 for p in parts[:-1]) and [p.start for p in parts] == [256 * i for i in range(len(parts))]
    for content in bins.values():
        at = 0
        for offset, length in sorted(content):
            assert offset == at
            at += length
        assert at <= 256
    assert [r.length for r in by_doc[100]] == [1] and len(by_doc[105]) == 2 and None in by_doc
    assert pk.pack(docs_of(rows).where("false"), pk.tokenizer_path()).isEmpty()


def test_best_fit_is_tightest_and_bounded():
    b = pk.BestFit(10, 2)
    assert [b.place(x) for x in (6, 7, 3, 4)] == [(0, 0), (1, 0), (1, 7), (0, 6)]
    assert b.open == 0
    for x in (6, 7):
        b.place(x)
    b.place(8)  # a third bin: the fullest (7) closes
    assert b.open == 2 and b.place(3)[0] != 3
    rng, b = random.Random(2), pk.BestFit(2048, 64)
    sizes = [rng.randint(1, 2048) for _ in range(5000)]
    fill: dict[int, int] = {}
    for s in sizes:
        n, at = b.place(s)
        assert at == fill.get(n, 0)
        fill[n] = at + s
        assert fill[n] <= 2048 and b.open <= 64
    assert len(fill) < 1.1 * sum(sizes) / 2048


def naive(sizes, size, most):
    """Best-fit by a scan of a list of open bins (free, opened at): (bin, offset) of each size."""
    bins, made, out = [], 0, []
    for s in sizes:
        fits = [b for b in bins if b[0] >= s]
        if fits:
            tight = min(b[0] for b in fits)
            best = [b for b in fits if b[0] == tight][-1]  # the one that came to this free space last
            bins.remove(best)
        else:
            best, made = (size, made), made + 1
        out.append((best[1], size - best[0]))
        if best[0] > s:
            if len(bins) >= most:
                full = min(b[0] for b in bins)
                bins.remove([b for b in bins if b[0] == full][-1])
            bins.append((best[0] - s, best[1]))
    return out


@pytest.mark.parametrize("seed", range(5))
def test_best_fit_is_the_naive_one(seed):
    rng = random.Random(seed)
    sizes = [rng.choice((1, 2, 50, rng.randint(1, 100))) for _ in range(800)]
    most = rng.choice((1, 3, 20, 1000))
    b = pk.BestFit(100, most)
    assert [b.place(s) for s in sizes] == naive(sizes, 100, most)


@pytest.mark.parametrize("parts", [1, 64])
def test_few_sequences(spark, sf2, parts):
    docs = spark.read.parquet(f"{sf2}/documents.parquet").repartition(parts)
    r = pk.pack(docs, pk.tokenizer_path()).selectExpr("count(distinct sequence_id) n", "sum(length) / 2048 least").first()
    assert r.n <= 1.01 * float(r.least) + 1


def test_texts_of_megabytes(spark, docs_of, tokenizer, words):
    rng = random.Random(3)
    texts = ["a" * 1_500_000, " ".join(rng.choice(words) for _ in range(400_000)), "x1é" * 200_000]
    got = pk.pack(docs_of(list(enumerate(texts))), pk.tokenizer_path()).groupBy("doc_id").agg({"length": "sum", "piece": "max"}).collect()
    want = {i: len(tokenizer.encode(t, add_special_tokens=False).ids) + 1 for i, t in enumerate(texts)}
    assert {r.doc_id: r["sum(length)"] for r in got} == want
    assert all(r["max(piece)"] == (want[r.doc_id] - 1) // 2048 for r in got)
