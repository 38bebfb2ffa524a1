"""Decontamination, URL filters, quality rules: results, odd rows, and no Python in their plans."""

import collections
import random
import re

import pytest

from ergodica.llm import decontaminate as dc
from pyspark.sql import functions as F

from ergodica.llm import queries, rules, urls


@pytest.mark.parametrize("name", ["op3_decontamination", "op7_url_filter", "op8_quality_rules"])
def test_plans_hold_no_python(spark, sf, name):
    plan = queries.queries()[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Pandas|Arrow|CartesianProduct", plan)


def test_planted_passages(spark, docs_of, words, odd, monkeypatch):
    rng = random.Random(1)
    text = lambda n: " ".join(rng.choice(words) for _ in range(n))
    items = [text(40) for _ in range(8)]
    bench = spark.createDataFrame([*enumerate(items), (8, "Short Item, of six words"), (9, None), (10, "")], "item_id long, text string")
    swap = lambda t, every: " ".join(rng.choice(words) if i % every == every - 1 else w for i, w in enumerate(t.split()))
    rows = [(1, f"{text(30)} {items[0]} {text(20)}"), (2, f"{text(10)}\n{swap(items[1], 7)}"), (3, items[2].upper().replace(" ", ", ")), (4, " ".join(items[3].split()[:30])), (5, text(200)), (6, " ".join(items[4].split()[:12])), (7, f"{text(9)} short item of six words {text(5)}"), (8, items[5] + " " + items[6]), *odd]
    docs = docs_of(rows)
    for bound in (1_000_000, 3):  # broadcast, and the shuffle beyond its bound
        monkeypatch.setattr(dc, "BROADCAST_SEEDS", bound)
        got = {r.doc_id: r for r in dc.decontaminate(docs, bench).collect()}
        assert {d for d, r in got.items() if r.contaminated} == {1, 2, 3, 4, 7, 8}
        assert got[1].item_id == 0 and got[2].item_id == 1 and got[2].matched < got[2].overlap == 40 and got[8].n_items == 2 and got[7].item_id == 8
        left = dc.clean(docs, bench)
        assert left.columns == docs.columns and left.count() == len(rows) - 6
    assert dc.decontaminate(docs, bench.where("false")).where("contaminated").isEmpty()
    assert dc.decontaminate(docs.where("false"), bench).isEmpty()


def test_long_parts_and_shifted_copies(spark, docs_of, words):
    rng = random.Random(2)
    text = lambda n: " ".join(rng.choice(words) for _ in range(n))
    items = [text(59), text(38), text(15)]
    bench = spark.createDataFrame([*enumerate(items)], "item_id long, text string")
    long, mid, short = (t.split() for t in items)
    around = lambda w: f"{text(20)} {' '.join(w)} {text(25)}"
    found = [
        around(long[:30]), around(long[10:45]), around(long[-20:]), around([*long[:29], "zz", *long[29:]]), around([*mid[:19], "zz", "yy", *mid[19:]]), around(long[:29] + long[30:]),
        around([*long[:20], text(60), *long[40:]]), around([w for i, w in enumerate(long) if i % 13]), around(short), around([*short[:12]]),
    ]
    kept = [around(long[:10]), around(mid[20:29]), around(short[3:10]), text(400), around([x for i, w in enumerate(long) for x in (w, *text(2).split())])]
    got = {r.doc_id: r for r in dc.decontaminate(docs_of(list(enumerate(found + kept))), bench).collect()}
    assert [got[i].contaminated for i in range(len(found + kept))] == [True] * len(found) + [False] * len(kept)
    assert (got[0].item_id, got[3].matched, got[4].item_id, got[4].matched, got[5].matched) == (0, 59, 1, 38, 58)
    assert 30 <= got[0].matched <= got[0].overlap


@pytest.mark.parametrize(("n", "swapped", "least"), [(15, 3, 1.0), (15, 4, 0.98), (15, 5, 0.95), (15, 6, 0.85), (20, 8, 0.93)])
def test_recall_of_substituted_items(spark, docs_of, n, swapped, least):
    rng = random.Random(n + swapped)
    text = lambda k: [f"w{rng.randrange(3000)}" for _ in range(k)]
    items = [text(n) for _ in range(200)]
    copies = [[f"x{i}" if i in out else w for i, w in enumerate(t)] for t in items for out in [set(rng.sample(range(n), swapped))]]
    docs = docs_of([(i, " ".join([*text(20), *c, *text(20)])) for i, c in enumerate(copies)])
    bench = spark.createDataFrame([(i, " ".join(t)) for i, t in enumerate(items)], "item_id long, text string")
    got = dc.decontaminate(docs, bench).where("contaminated and item_id = doc_id").count()
    assert got >= least * len(items)


def test_dense_substitution_and_a_split_short_item(spark, docs_of):
    words = [f"w{i}" for i in range(45)]
    bench = spark.createDataFrame([(0, " ".join(words)), (1, " ".join(f"v{i}" for i in range(15)))], "item_id long, text string")
    every = lambda k: " ".join("x" if i % k == k - 1 else w for i, w in enumerate(words))
    split = " ".join([*(f"v{i}" for i in range(7)), "x", *(f"v{i}" for i in range(7, 15))])
    got = {r.doc_id: r.item_id for r in dc.decontaminate(docs_of([(0, every(3)), (1, split), (2, every(2))]), bench).collect()}
    assert got == {0: 0, 1: 1, 2: None}


@pytest.mark.parametrize("seed", range(2))
def test_decontamination_is_the_rule_of_brute_force(spark, docs_of, words, odd, contaminates, seed):
    """Items of 4 to 60 words, copied whole or in part, with words substituted, inserted and left out: every (document, item) as judged alone."""
    from ergodica.llm import decontaminate as dc

    rng = random.Random(seed)
    some = words[:400]  # chance meetings too
    text = lambda n: [rng.choice(some) for _ in range(n)]
    items = [text(rng.choice((4, 10, 11, 15, 20, 38, 59))) for _ in range(12)]
    rows = []
    for k in range(90):
        it = rng.choice(items)
        a = rng.randrange(len(it))
        part = it if rng.random() < 0.5 else it[a : a + rng.randint(3, len(it))]
        part = [w if rng.random() > rng.choice((0, 0.1, 0.3, 0.5)) else rng.choice(some) for w in part]
        if rng.random() < 0.4:
            part.insert(rng.randrange(len(part) + 1), rng.choice(some))
        if rng.random() < 0.3 and len(part) > 1:
            part.pop(rng.randrange(len(part)))
        rows.append((k, " ".join(text(rng.randint(0, 30)) + part + text(rng.randint(0, 30)))))
    rows += [(200, " ".join(text(40_000)))] + [r for r in odd if r[0] is not None and r[0] != 105]
    bench = spark.createDataFrame([(i, " ".join(t)) for i, t in enumerate(items)] + [(50, None), (51, "")], "item_id long, text string")
    got = {(r.doc_id, r.item_id) for r in dc.contaminations(docs_of(rows), bench).collect()}
    want = {(d, i) for d, t in rows for i, it in enumerate(items) if contaminates(t, " ".join(it))}
    assert got == want and len(want) > 30


def test_public_suffixes_ports_and_users(spark):
    rows = [("a.b.co.uk",), ("u@a.b.co.uk:80",), ("co.uk",), ("x.org:8080",), ("",), ("a..b",)]
    d, s = urls.levels(F.col("host"), ["co.uk", "uk"])
    plain = urls.levels(F.col("host"))
    got = [tuple(r) for r in spark.createDataFrame(rows, "host string").select(d, s, plain[0]).collect()]
    assert got == [("b.co.uk", "co.uk", "co.uk"), ("b.co.uk", "co.uk", "co.uk"), ("co.uk", "co.uk", "co.uk"), ("x.org", "org", "x.org"), ("", "", ""), (".b", "b", ".b")]


def test_hot_host_is_not_gathered(spark):
    """A host with most of the pages: its pages stay where they are."""
    pages = spark.createDataFrame([(i, f"http://{'hot' if i % 3 else f'h{i}'}.org/{i}", "") for i in range(3000)], "page_id long, url string, html string")
    got = urls.judge(pages, spark.createDataFrame([(i, int(i % 3 > 0)) for i in range(600)], "page_id long, bad int"), rules=())
    assert got.count() == 3000 and got.where("host = 'hot.org' and verdict = 'block'").count() == 2000 and "BroadcastNestedLoopJoin" not in got._jdf.queryExecution().executedPlan().toString()


def test_url_parts_and_rules(spark):
    rows = [
        (1, "http://A.Example.NET/en/x?y#z"), (2, "https://example.net"), (3, "https://x.net/fr/"), (4, "http://b.example.com/de/1"), (5, "http://b.example.com/d"), (6, "ftp://x.org/fr/a"), (7, "http://org?x=/fr/"),
        (8, None), (9, "no scheme"), (10, ""), (11, "http://notexample.com/de/"), (12, "://"), (None, "http://h.com/"), (1, "http://A.Example.NET/en/x?y#z"),
    ]
    pages = spark.createDataFrame([(*r, "h", "clash") for r in rows], "page_id long, url string, html string, mean string")
    none = spark.createDataFrame([], "page_id long, bad int")
    got = {r.page_id: r for r in urls.judge(pages, none).collect()}
    want = {
        1: ("a.example.net", "/en/x", "example.net/en/", "allow"), 2: ("example.net", "", None, "allow"), 3: ("x.net", "/fr/", "net/", "block"), 4: ("b.example.com", "/de/1", "example.com/de/", "block"), 5: ("b.example.com", "/d", None, "allow"),
        6: ("x.org", "/fr/a", "org/fr/", "allow"), 7: ("org", "", None, "allow"), 8: ("", "", None, "allow"), 9: ("", "", None, "allow"), 10: ("", "", None, "allow"), 11: ("notexample.com", "/de/", None, "allow"), 12: ("", "", None, "allow"),
    }
    assert {i: tuple(got[i])[1:5] for i in want} == want
    assert urls.judge(pages, none).count() == len(rows) and urls.judge(pages.where("false"), none).isEmpty()


def test_reputation_shrinks(spark):
    pages = [(i, f"http://bad.spam.biz/{i}") for i in range(60)] + [(100 + i, f"http://good.fine.biz/{i}") for i in range(60)] + [(200, "http://new.spam.biz/"), (201, "http://new.fine.biz/"), (202, "http://other.biz/"), (203, "http://one.fine.biz/")]
    bad = [(i, 1) for i in range(60)] + [(100 + i, 0) for i in range(60)] + [(203, 1), (999, 1), (5, None)]
    got = {r.page_id: r for r in urls.judge(spark.createDataFrame([(*p, "") for p in pages], "page_id long, url string, html string"), spark.createDataFrame(bad, "page_id long, bad int"), rules=()).collect()}
    assert got[0].verdict == "block" and got[100].verdict == "allow" and got[0].posterior > 0.9 > 0.1 > got[100].posterior
    assert got[200].posterior > 0.8 and got[201].posterior < 0.2  # unknown hosts follow their domain
    assert got[201].posterior < got[203].posterior < 1 and got[203].verdict == "allow"  # one bad page does not condemn a host
    assert 0.3 < got[202].posterior < 0.7


def expected(t):
    t = t or ""
    w, lines = re.findall(r"[^\x20\x09-\x0D]+", t), [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    c, cover = collections.Counter(zip(w, w[1:], w[2:], strict=False)), set()
    for i in range(len(w) - 2):
        if c[tuple(w[i : i + 3])] > 1:
            cover |= {i, i + 1, i + 2}
    failed = len(w) < 50 or 100 * len(cover) > 50 * len(w)
    return len(w), sum(map(len, w)), sum(x in "#*$%&|<>" for x in t), len(lines) - len(set(lines)), len(cover), failed


def test_quality_counts_and_verdict(spark, docs_of, odd, sf):
    real = [(r.doc_id, r.text, r.lang) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    rows = real + [(1000 + (d or 0), t) for d, t in odd] + [(5000, "a b c a b c a b\na b\n \na b\n#$ |"), (5001, "| " * 60), (5002, real[0][1] + "\n" + real[0][1], None), (None, "x y", None)]
    got = rules.judge(docs_of(rows)).collect()
    assert len(got) == len(rows)
    texts = collections.defaultdict(set)
    for r in rows:
        texts[r[0]].add(expected(r[1]))
    for r in got:
        assert tuple(r)[1:7] in texts[r.doc_id]
        assert r.kept <= (not r.base_failed)
    by = {r.doc_id: r for r in got}
    assert not by[5001].kept and not by[5000].kept
    assert rules.judge(docs_of(rows).where("false")).isEmpty()
    assert rules.judge(docs_of([(1, real[0][1], None)])).first().kind_distance == 0


def test_equal_hashes_are_not_equal_windows(spark, docs_of, monkeypatch):
    monkeypatch.setattr(rules, "_PLACE", 62)  # two bits of hash are left: nearly every window is a candidate
    text = " ".join(f"w{i % 50}" for i in range(120))
    r = rules.base_counts(docs_of([(1, text)]), ["doc_id"]).first()
    assert r.n_repeat_words == expected(text)[4]
