"""Chains of factors on packed blocks, and products of two steps, on tables that fall apart into copies with shifted keys."""

import os

import numpy as np
import pytest
from pyspark.sql import functions as F

from ergodica import oracles, queries
from ergodica.operators import builders, packed, solve
from ergodica.operators import chain as C
from ergodica.plans import planner
from verify import connect, rows_of, same


@pytest.fixture(scope="module")
def copies(tmp_path_factory, sf2):
    """Two copies of the tables, keys shifted: no line joins them; the second has only a part of its lines, so the shares differ."""
    out, con = tmp_path_factory.mktemp("copies"), connect(sf2)
    shifted = {"orders": {"o_orderkey": 15_000, "o_custkey": 1_500}, "lineitem": {"l_orderkey": 15_000, "l_partkey": 2_000, "l_suppkey": 100}}
    for name in os.listdir(sf2):
        t = name.split(".")[0]
        more = ", ".join(f"{k} + i.range * {v} AS {k}" for k, v in shifted.get(t, {}).items())
        con.execute(f"COPY (SELECT t.* {f'REPLACE ({more})' if more else ''} FROM {t} t{', range(2) i' if more else ''}{' WHERE i.range = 0 OR l_linenumber < 4' if t == 'lineitem' else ''}) TO '{out}/{name}'")
    return str(out)


def equals_sql(spark, d, name):
    got, want = queries.queries()[name](spark, d).toPandas(), connect(d).execute(oracles.oracle_sql()[name]).df()
    assert same(rows_of(got), rows_of(want))


def test_bipartite_walk_on_copies(spark, copies):
    equals_sql(spark, copies, "bipartite_lazy")


def test_packed_equals_stored(spark, monkeypatch):
    rng = np.random.default_rng(3)
    rows = [(int(a), int(b), float(w)) for a, b, w in zip(rng.integers(0, 12, 90) * 7, rng.integers(0, 12, 90) * 7, rng.random(90) + 0.1)]
    rows += [(i * 7, (i + 1) % 12 * 7, 300.0) for i in range(12)]
    w = spark.createDataFrame(rows, "src long, dst long, w double")
    chain = C.FactoredChain((w, w), 0.25)
    monkeypatch.setattr(packed, "BLOCK_EDGES", 16)
    got, want = ({r.state: r.pi for r in solve.solve(chain, 2, check_every=5, engine=e).pi.collect()} for e in ("auto", "local"))
    assert got.keys() == want.keys() and max(abs(got[k] - want[k]) for k in got) < 1e-8
    assert not packed.fits(10**8, 4)
    with pytest.raises(Exception, match="without exits"):
        solve.solve(C.FactoredChain((w.where("src > 0"),)), 1)


def test_two_step_walk_on_copies(spark, copies):
    equals_sql(spark, copies, "supplier_two_step")


def test_two_step_edges_in_blocks(spark, copies):
    """Small blocks and a hub give the edges of the plain join; no plan sums products by pairs of states."""
    ab = spark.createDataFrame([(a, b, float(1 + (a * b) % 3)) for a in range(30) for b in range(11) if a == 4 or (a + b) % 4 == 0], "a long, b long, w double")
    bc = ab.select("b", F.col("a").alias("c"), "w")
    got = builders.two_step(ab, bc, block_rows=9)
    pairs = ab.join(bc.withColumnRenamed("w", "v"), "b").join(bc.groupBy("b").agg(F.sum("w").alias("t")), "b")
    want = C.normalise(pairs.groupBy(F.col("a").alias("src"), F.col("c").alias("dst")).agg(F.sum(F.expr("w * v / t")).alias("w")), keep_counts=True)
    both = got.join(want.select("src", "dst", F.col("w").alias("w2"), F.col("prob").alias("p2")), ["src", "dst"], "full_outer")
    assert got.count() == want.count() and both.where("w2 is null or w is null or abs(w - w2) > 1e-12 or abs(prob - p2) > 1e-12").isEmpty()
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "FlatMapGroupsInArrow" in plan and "HashAggregate(keys=[a" not in plan
    assert builders.two_step(ab.where("false"), bc).isEmpty()
    equals_sql(spark, copies, "two_step_edges")


def test_word_chain_in_blocks(spark, tmp_path, monkeypatch):
    """Two vocabularies that never meet, words that mostly follow themselves, a word that does nothing else, rows without words: as SQL has it, in one task
    and over blocks; the stored chain, for more words than fit, has the same transitions."""
    texts = ["the cat and the dog and the end " + "so " * 700 + "the", "Le chat et le chien, et " + "ha " * 900 + "la fin et le", "the end and so the cat", "le chien et la", "um um um", "um", "", None, "..!"]
    spark.createDataFrame([(i, x) for i, x in enumerate(texts)], "doc_id long, text string").repartition(3).write.parquet(f"{tmp_path}/documents.parquet")
    d = str(tmp_path)

    def con():
        import duckdb

        c = duckdb.connect()
        c.execute(f"CREATE VIEW documents AS SELECT * FROM '{d}/documents.parquet/*.parquet'")
        return c

    want = rows_of(con().execute(oracles.oracle_sql()["word_chain_top100"]).df())
    assert len(want) == 13
    for edges in (planner.LOCAL_EDGES, 0):
        monkeypatch.setattr(planner, "LOCAL_EDGES", edges)
        monkeypatch.setattr(packed, "BLOCK_EDGES", 1 << 20 if edges else 300)
        monkeypatch.setattr(packed, "PIECE_VISITS", 1 << 22 if edges else 1)
        assert same(rows_of(queries.queries()["word_chain_top100"](spark, d).toPandas()), want)
    docs = spark.read.parquet(f"{d}/documents.parquet")
    c = builders.word_chain(docs).stored()
    name = lambda x: c.states.select(F.col("state").alias(x), F.col("label").alias(f"{x}_word"))
    got = c.edges.join(name("src"), "src").join(name("dst"), "dst").select("src_word", "dst_word", F.round("prob", 12)).collect()
    plain = C.normalise(builders.word_succession(docs).where("src <> 'um'")).select("src", "dst", F.round("prob", 12)).collect()
    assert sorted(map(tuple, got)) == sorted(map(tuple, plain))
    nothing = builders.word_chain(docs.where("doc_id > 3"))
    assert solve.solve(nothing, 1, 8).pi.isEmpty() and solve.solve(builders.word_chain(docs.where("false")), 1, 8).pi.isEmpty()


def test_word_chain_beside_the_driver(spark, monkeypatch):
    """Over ranges no vector of all words reaches the driver: nothing is broadcast or collected as Arrow."""
    texts = ["a b c a d " + "a " * 30, "b d e a", "x y x z x", "q q q", "", None]
    docs = spark.createDataFrame([(i, x) for i, x in enumerate(texts * 3)], "doc_id long, text string").repartition(2)

    def refuse(*_, **__):
        raise AssertionError("the driver would hold all words")

    monkeypatch.setattr(planner, "LOCAL_EDGES", 0)
    monkeypatch.setattr(packed, "BLOCK_EDGES", 30)
    chain = builders.word_chain(docs)
    with monkeypatch.context() as m:
        m.setattr(type(docs), "toArrow", refuse)
        m.setattr(type(spark.sparkContext), "broadcast", refuse)
        r = solve.solve(chain, 1, 3, check_every=12, on_limit="raise")
    words = " ".join(x for x in texts if x and x != "q q q").split()
    got = {row.label: row.pi for row in r.pi.collect()}
    assert r.converged and got.keys() == set(words) and all(abs(got[w] - words.count(w) / len(words)) < 1e-8 for w in got)


def test_packed_weights():
    for most, size in ((255, 1), (256, 2), (1 << 16, 4), (0.5, 8), (1 << 33, 8)):
        assert len(packed.packed_weights(np.array([1.0, most]))) == 2 * size
