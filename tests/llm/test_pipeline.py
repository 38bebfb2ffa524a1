"""Each stage on its own input, against what brute force says of it; and every llm query that has SQL."""

import pytest

import corpus_pipeline as cp
from ergodica.llm import neardup, queries, sql
from verify import connect, rows_of, same


@pytest.fixture(scope="module")
def outputs(spark, sf):
    docs, kept = spark.read.parquet(f"{sf}/documents.parquet"), {}
    kept["documents"] = docs
    for name, stage in cp.STAGES:
        kept[name] = docs = cp.written(stage(spark, docs, sf), name)
    return kept


def ids(df):
    return sorted(r.doc_id for r in df.select("doc_id").distinct().collect())


def test_stages(spark, outputs, sf, contaminates):
    docs = outputs["documents"]
    for name in ("language_id", "near_dedup", "substring_dedup", "decontamination"):
        assert outputs[name].columns == docs.columns
    assert len(ids(outputs["language_id"])) >= 0.98 * docs.count()
    before = [(r.doc_id, r.text) for r in outputs["language_id"].collect()]
    sets = {d: neardup.shingle_set(neardup.words_of(t), 5) for d, t in before}
    gone = set()
    parent = {d: d for d in sets}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    order = sorted(sets)
    for k, a in enumerate(order):
        for b in order[k + 1 :]:
            if sets[a] and sets[b] and 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]):
                x, y = sorted((root(a), root(b)))
                parent[y] = x
    gone = {d for d in order if root(d) != d}
    assert ids(outputs["near_dedup"]) == sorted(set(order) - gone)
    first: dict[tuple, int] = {}
    split = {r.doc_id: (r.text or "").encode().split() for r in outputs["near_dedup"].collect()}
    for d in sorted(split):
        for i in range(len(split[d]) - 12):
            first.setdefault(tuple(split[d][i : i + 13]), d)
    want = {}
    for d, w in split.items():
        cut = {i + j for i in range(len(w) - 12) if first[tuple(w[i : i + 13])] < d for j in range(13)}
        if not cut or len(cut) < len(w):
            want[d] = [x for i, x in enumerate(w) if i not in cut]
    cut_texts = {r.doc_id: r.text for r in outputs["substring_dedup"].collect()}
    assert {d: (t or "").encode().split() for d, t in cut_texts.items()} == want
    bench = [r.text for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    assert ids(outputs["decontamination"]) == sorted(d for d, t in cut_texts.items() if not any(contaminates(t, b) for b in bench))


def test_packing_holds_every_token(outputs):
    import numpy as np
    from tokenizers import Tokenizer

    from ergodica.llm import packing

    tokenizer, pieces = Tokenizer.from_file(packing.tokenizer_path()), {}
    for r in outputs["best_fit_packing"].collect():
        pieces.setdefault(r.doc_id, {})[r.piece] = r.ids
    texts = {r.doc_id: r.text for r in outputs["decontamination"].collect()}
    assert pieces.keys() == texts.keys()
    for d, t in texts.items():
        assert np.concatenate([pieces[d][k] for k in sorted(pieces[d])]).tolist() == [*tokenizer.encode(t or "", add_special_tokens=False).ids, 0]


def test_odd_rows_through_every_stage(spark, docs_of, odd, words, sf):
    """Nulls, empty texts, repeated rows, clashing names and an empty table; a text of megabytes."""
    long = " ".join(words[i * i % 2999] for i in range(300_000))
    docs = docs_of([*odd, (1, " ".join(words[:80])), (2, " ".join(words[:80])), (3, long), (4, None)])
    for table in (docs, docs.where("false")):
        now = table
        for name, stage in cp.STAGES:
            now = cp.written(stage(spark, now, sf), name)
            if name != "best_fit_packing":
                assert now.columns == docs.columns
        left = {r.doc_id for r in now.select("doc_id").distinct().collect()}
        assert left == set() if table is not docs else {1, 3, 103} <= left and not left & {2, 4, 100, 101, 102}


def test_run(spark, sf, outputs):
    got = cp.run(spark, sf)
    assert got.count() == outputs["best_fit_packing"].count()
    assert [n for n, _ in cp.STAGES] and cp.ORACLE_SQL is None


@pytest.mark.parametrize("name", sorted(sql.oracle_sql()))
def test_equals_sql(spark, sf, name):
    got, want = queries.queries()[name](spark, sf).toPandas(), connect(sf).execute(sql.oracle_sql()[name]).df()
    assert sorted(got.columns) == sorted(want.columns) and same(rows_of(got), rows_of(want))
