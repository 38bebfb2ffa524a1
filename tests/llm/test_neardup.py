import random

import numpy as np
import pytest

from ergodica.llm import components as cc
from ergodica.llm import neardup as nd


def brute(rows, n, num=4, den=5):
    sets = {}
    for i, t in rows:
        if i is not None:
            sets.setdefault(i, []).append(nd.shingle_set(nd.words_of(t), n))
    ids = sorted(sets)
    parent = {i: i for i in ids}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for k, a in enumerate(ids):
        for b in ids[k + 1 :]:
            for s in sets[a]:
                for t in sets[b]:
                    if s and t and den * len(s & t) >= num * len(s | t):
                        x, y = sorted((root(a), root(b)))
                        parent[y] = x
    return {i: root(i) for i in ids}


@pytest.fixture(scope="module")
def rows(words):
    rng = random.Random(1)
    out, at = [], 0
    for _ in range(12):
        base = [rng.choice(words) for _ in range(rng.randint(5, 120))]
        for _ in range(rng.randint(1, 9)):
            copy = list(base)
            for _ in range(rng.randint(0, max(1, len(base) // 25))):
                copy[rng.randrange(len(copy))] = rng.choice(words)
            out.append((at, " ".join(copy)))
            at += 1
    chain = [rng.choice(words) for _ in range(100)]  # neighbours are similar, the ends are not
    for step in range(15):
        chain = chain[4:] + [rng.choice(words) for _ in range(4)]
        out.append((at, " ".join(chain)))
        at += 1
    return out


@pytest.mark.parametrize("n", [2, 5])
def test_equals_brute_force(spark, docs_of, rows, odd, n):
    got = nd.near_duplicates(docs_of(rows + odd), n).collect()
    want = brute(rows + odd, n)
    assert len(got) == len(rows + odd)
    for r in got:
        if r.doc_id is None:
            assert r.component_id is None and r.kept
        else:
            assert r.component_id == want[r.doc_id] and r.kept == (r.doc_id == r.component_id)
    assert {r.doc_id: r.n_shingles for r in got}[100] == 0


def test_exact_rest_finds_what_hubs_miss(spark, docs_of, rows, monkeypatch):
    monkeypatch.setattr(nd, "HUB_ROUNDS", 1)
    monkeypatch.setattr(nd, "BLOCK", 3)
    got = {r.doc_id: r.component_id for r in nd.near_duplicates(docs_of(rows), 2).collect()}
    assert got == brute(rows, 2)


def test_keep_one(spark, docs_of, rows, odd):
    docs = docs_of(rows + odd)
    kept = nd.keep_one(docs, 2)
    want = brute(rows + odd, 2)
    assert kept.columns == docs.columns
    assert sorted({r.doc_id for r in kept.collect() if r.doc_id is not None}) == sorted({i for i, c in want.items() if i == c})
    assert nd.near_duplicates(docs.where("false")).isEmpty()


def test_signature_is_unbiased_and_stops_early():
    rng = np.random.default_rng(2)
    errors = []
    for _ in range(60):
        a = rng.integers(0, 2**62, 400, dtype=np.uint64)
        b = np.concatenate([a[80:], rng.integers(0, 2**62, 80, dtype=np.uint64)])
        s = nd.superminhash(np.concatenate([a, b]), np.repeat([0, 1], 400), 2)
        errors.append((s[0] == s[1]).mean() - 320 / 480)
    assert abs(np.mean(errors)) < 0.02
    assert (s < nd.REGISTERS << 32).all()
    one = nd.superminhash(np.array([7], np.uint64), np.array([0]), 2)
    assert sorted(one[0] >> 32) == list(range(nd.REGISTERS)) and (one[1] == np.iinfo(np.int64).max).all()


def test_spanning_links_equal_brute_force():
    rng = np.random.default_rng(3)
    sets = [np.unique(rng.integers(0, 12, rng.integers(1, 12)).astype(np.uint64)) for _ in range(30)]
    block, comp = np.arange(30) % 2, np.arange(30)
    links = nd.spanning_links(np.arange(30), comp, block, sets, 4, 5)
    for a, b in links:
        x, y = set(sets[a].tolist()), set(sets[b].tolist())
        assert 5 * len(x & y) >= 4 * len(x | y)


def test_components(spark):
    rng = random.Random(4)
    links = [(i, i + 1) for i in range(40)] + [(100 + i, 100) for i in range(30)] + [(rng.randrange(200, 230), rng.randrange(200, 230)) for _ in range(15)] + [(5, 5)]
    got = {r.node: r.component for r in cc.components(spark.createDataFrame(links, "a long, b long")).collect()}
    near: dict[int, set] = {}
    for a, b in links:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    for node, c in got.items():
        seen, todo = {node}, [node]
        while todo:
            for x in near[todo.pop()] - seen:
                seen.add(x)
                todo.append(x)
        assert c == min(seen)
    assert cc.components(spark.createDataFrame([], "a long, b long")).isEmpty()
