"""DuckDB SQL for the rows of those queries that SQL can express."""

from __future__ import annotations

from .rules import COMMON, KINDS, LEAST_WORDS, MOST_KIND, MOST_WORD
from .urls import LEAST_STRENGTH, MOST_BAD, MOST_STRENGTH, RULES, Z

WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"
LOWER = "translate({}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"


def op2(n: int = 2) -> str:
    """Exact similarities of all pairs that share a shingle, and the least id reachable."""
    parts = " || ' ' || ".join(f"w[i + {k}]" for k in range(n))
    return f"""WITH RECURSIVE d AS (SELECT doc_id, {WORDS.replace("coalesce(text, '')", LOWER.format("coalesce(text, '')"))} AS w FROM documents),
    s AS (SELECT DISTINCT doc_id, {parts} AS s FROM (SELECT doc_id, w, unnest(range(1, len(w) - {n - 2})) AS i FROM d WHERE len(w) >= {n}) UNION SELECT doc_id, array_to_string(w, ' ') FROM d WHERE len(w) BETWEEN 1 AND {n - 1}),
    n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
    g AS (SELECT doc_id, n, md5(string_agg(s, chr(10) ORDER BY s)) AS h FROM s JOIN n USING (doc_id) GROUP BY ALL), r AS (SELECT h, min(doc_id) AS rep, any_value(n) AS n FROM g GROUP BY 1),
    q AS (SELECT s.doc_id, s.s, r.n FROM s JOIN r ON r.rep = s.doc_id),
    p AS (SELECT a.doc_id AS a, b.doc_id AS b FROM q a JOIN q b ON a.s = b.s AND a.doc_id < b.doc_id AND 5 * least(a.n, b.n) >= 4 * greatest(a.n, b.n) GROUP BY a.doc_id, b.doc_id, a.n, b.n HAVING 100 * count(*) >= 80 * (a.n + b.n - count(*))),
    e AS (SELECT a, b FROM p UNION ALL SELECT b, a FROM p), c AS (SELECT rep AS node, rep AS seen FROM r UNION SELECT c.node, e.b FROM c JOIN e ON e.a = c.seen),
    m AS (SELECT node, min(seen) AS component FROM c GROUP BY 1)
    SELECT d.doc_id, coalesce(g.n, 0) AS n_shingles, coalesce(m.component, d.doc_id) AS component_id, coalesce(m.component, d.doc_id) = d.doc_id AS kept
    FROM d LEFT JOIN g ON g.doc_id = d.doc_id LEFT JOIN r ON r.h = g.h LEFT JOIN m ON m.node = r.rep"""


def op6(window: int = 13) -> str:
    parts = " || ' ' || ".join(f"w[i + {k}]" for k in range(window))
    return f"""WITH d AS (SELECT doc_id, {WORDS} AS w FROM documents),
    x AS (SELECT doc_id, i, {parts} AS s FROM (SELECT doc_id, w, unnest(range(1, len(w) - {window - 2})) AS i FROM d WHERE len(w) >= {window})),
    f AS (SELECT s, min(doc_id) AS first FROM x GROUP BY 1 HAVING count(*) > 1),
    g AS (SELECT DISTINCT doc_id, unnest(range(i, i + {window})) AS i FROM (SELECT x.doc_id, x.i FROM x JOIN f ON f.s = x.s AND f.first < x.doc_id)),
    l AS (SELECT doc_id, list(i) AS gone FROM g GROUP BY 1),
    k AS (SELECT d.doc_id, w, coalesce(len(gone), 0) AS n_removed, CASE WHEN gone IS NULL THEN w ELSE list_filter(w, lambda t, i: NOT list_contains(gone, i)) END AS kept FROM d LEFT JOIN l USING (doc_id))
    SELECT doc_id, len(w) AS n_words, n_removed, sha256(array_to_string(kept, ' ')) AS kept_sha256 FROM k"""


def op7() -> str:
    """Rules by their length; posteriors level by level."""
    rule = "CASE " + " ".join(f"WHEN (host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{p}') THEN '{{{i}}}'" for i, (_, h, p) in enumerate(sorted(RULES, key=lambda r: -len(r[1] + r[2])))) + " END"
    ordered = sorted(RULES, key=lambda r: -len(r[1] + r[2]))
    named = rule.format(*(h + p for _, h, p in ordered))
    acted = rule.format(*(a for a, _, _ in ordered))

    def level(key: str, parent: str, prior: str) -> str:
        return f"""c_{key} AS (SELECT h.{key}, h.{parent}, sum(n) AS n, sum(bad) AS bad FROM h GROUP BY ALL), a_{key} AS (SELECT c.*, p.mean AS m FROM c_{key} c JOIN {prior} p USING ({parent})),
        f_{key} AS (SELECT sum((bad - n * m) * (bad - n * m) / n) AS spread, sum(m * (1 - m)) AS noise, sum((n - 1) * m * (1 - m)) AS room FROM a_{key}),
        r_{key} AS (SELECT CASE WHEN room > 0 THEN (spread - noise) / room ELSE 0 END AS rho FROM f_{key}),
        k_{key} AS (SELECT round(CASE WHEN rho > 0 THEN least(greatest(1 / rho - 1, {LEAST_STRENGTH}), {MOST_STRENGTH}) ELSE {MOST_STRENGTH} END, 6) AS k FROM r_{key}),
        b_{key} AS (SELECT {key}, {parent}, k * m + bad AS a, k * (1 - m) + n - bad AS b FROM a_{key}, k_{key}),
        p_{key} AS (SELECT {key}, {parent}, round(a / (a + b), 9) AS mean, round(a * b / ((a + b) * (a + b) * (a + b + 1)), 12) AS variance FROM b_{key})"""

    part = lambda k: f"array_to_string(list_slice(string_split(host, '.'), -{k}, -1), '.')"
    return f"""WITH u AS (SELECT page_id, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
    l AS (SELECT page_id, {LOWER.format("regexp_extract(coalesce(rest, ''), '^([^/?#]*)', 1)")} AS host, regexp_extract(coalesce(rest, ''), '^[^/?#]*(/[^?#]*)?', 1) AS path FROM u),
    t AS (SELECT *, {part(2)} AS domain, {part(1)} AS suffix, 0 AS every FROM l),
    o AS (SELECT doc_id AS page_id, CASE WHEN toxic = 1 OR quality = 0 THEN 1 WHEN quality = 1 THEN 0 END AS bad FROM labels),
    h AS (SELECT host, domain, suffix, every, count(*) AS n, sum(bad) AS bad FROM t JOIN o USING (page_id) WHERE bad IS NOT NULL GROUP BY ALL),
    z AS (SELECT every, sum(bad) + 0.5 AS a, sum(n) - sum(bad) + 0.5 AS b FROM h GROUP BY 1), p_every AS (SELECT every, round(a / (a + b), 9) AS mean, round(a * b / ((a + b) * (a + b) * (a + b + 1)), 12) AS variance FROM z),
    {level("suffix", "every", "p_every")}, {level("domain", "suffix", "p_suffix")}, {level("host", "domain", "p_domain")},
    j AS (SELECT t.*, coalesce(ph.mean, pd.mean, ps.mean, pe.mean) AS mean, coalesce(ph.variance, pd.variance, ps.variance, pe.variance) AS variance
        FROM t LEFT JOIN p_host ph USING (host) LEFT JOIN p_domain pd ON pd.domain = t.domain LEFT JOIN p_suffix ps ON ps.suffix = t.suffix LEFT JOIN p_every pe ON pe.every = t.every),
    v AS (SELECT *, round(mean - {Z} * sqrt(variance), 6) AS bound FROM j)
    SELECT page_id, host, path, {named} AS rule, coalesce({acted}, CASE WHEN bound > {MOST_BAD} THEN 'block' ELSE 'allow' END) AS verdict, round(mean, 6) AS posterior, bound FROM v"""


def op8() -> str:
    """Base counts by lists; divergences by joins of bins."""
    half = lambda p, q: f"((CASE WHEN {p} > 0 THEN {p} * log2({p} / (({p} + {q}) / 2)) ELSE 0 END) + (CASE WHEN {q} > 0 THEN {q} * log2({q} / (({p} + {q}) / 2)) ELSE 0 END)) / 2"
    kinds = {"lower": "[^a-z]+", "upper": "[^A-Z]+", "digit": "[^0-9]+", "beyond": r"[\x00-\x7F]+"}
    gone = lambda p: f"length(regexp_replace(t, '{p}', '', 'g'))"
    bins = " + ".join(half(f"(b.{k} * 1.0 / b.n)", f"(r.{k} * 1.0 / r.n)") for k in KINDS)
    return rf"""WITH d AS (SELECT row_number() OVER () AS r, doc_id, lang, coalesce(text, '') AS t, {WORDS} AS w FROM documents),
    x AS (SELECT r, i, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] AS s FROM (SELECT r, w, unnest(range(1, len(w) - 1)) AS i FROM d WHERE len(w) >= 3)),
    m AS (SELECT r, s FROM x GROUP BY ALL HAVING count(*) > 1), c AS (SELECT r, count(DISTINCT k) AS n FROM (SELECT x.r, unnest([i, i + 1, i + 2]) AS k FROM x JOIN m ON m.r = x.r AND m.s = x.s) GROUP BY 1),
    a AS (SELECT d.r, doc_id, lang, w, len(w) AS n_words, length(t) AS n, length(regexp_replace(t, '[\x20\x09-\x0D]+', '', 'g')) AS word_chars, length(regexp_replace(t, '[^#*$%&|<>]+', '', 'g')) AS n_symbols,
        {", ".join(f"{gone(p)} AS {k}" for k, p in kinds.items())}, list_filter(string_split(t, chr(10)), lambda l: regexp_matches(l, '[^\x20\x09-\x0D]')) AS lines, coalesce(c.n, 0) AS n_repeat_words FROM d LEFT JOIN c ON c.r = d.r),
    b AS (SELECT *, len(lines) - len(list_distinct(lines)) AS n_dup_lines, n - word_chars AS space, word_chars - lower - upper - digit - beyond AS other FROM a),
    r AS (SELECT lang, {", ".join(f"sum({k}) AS {k}" for k in KINDS)}, sum(n) AS n FROM b WHERE lang IS NOT NULL GROUP BY 1),
    kd AS (SELECT b.r, min(round(sqrt(greatest({bins}, 0)), 6)) AS kind FROM b, r WHERE b.n_words >= {LEAST_WORDS} GROUP BY 1),
    e AS (SELECT lang, lower(v) AS v, count(*) AS c FROM (SELECT lang, unnest(w) AS v FROM d WHERE lang IS NOT NULL) GROUP BY ALL),
    tot AS (SELECT lang, sum(c) AS total FROM e GROUP BY 1), top AS (SELECT lang, v, c * 1.0 / total AS q FROM e JOIN tot USING (lang) QUALIFY row_number() OVER (PARTITION BY lang ORDER BY c DESC, v) <= {COMMON}),
    qs AS (SELECT lang, sum(q) AS q FROM top GROUP BY 1),
    f AS (SELECT r, lower(v) AS v, count(*) AS c FROM (SELECT r, unnest(w) AS v FROM d) GROUP BY ALL),
    h AS (SELECT f.r, top.lang, sum(f.c * 1.0 / b.n_words) AS mass, sum({half("(f.c * 1.0 / b.n_words)", "top.q")} - top.q / 2) AS part FROM f JOIN top ON top.v = f.v JOIN b ON b.r = f.r GROUP BY ALL),
    wd AS (SELECT b.r, min(round(sqrt(greatest(coalesce(part, 0) + qs.q / 2 + {half("greatest(1 - coalesce(mass, 0), 0)", "greatest(1 - qs.q, 0)")}, 0)), 6)) AS word
        FROM b CROSS JOIN qs LEFT JOIN h ON h.r = b.r AND h.lang = qs.lang WHERE b.n_words >= {LEAST_WORDS} GROUP BY 1),
    z AS (SELECT b.*, coalesce(kind, 0.0) AS kind_distance, coalesce(word, 0.0) AS word_distance, b.n_words < 50 OR 100 * n_repeat_words > 50 * b.n_words AS base_failed FROM b LEFT JOIN kd ON kd.r = b.r LEFT JOIN wd ON wd.r = b.r)
    SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND kind_distance <= {MOST_KIND} AND word_distance <= {MOST_WORD} AS kept, kind_distance, word_distance FROM z"""


def op9() -> str:
    bits = "('0x' || substr(h, {0}, 5))::INT"
    alphabet = "'ABCDEFGHIJKLMNOPQRSTUVWXYZ234567'"
    letters = " || ".join(f"substr({alphabet}, ((({bits.format(5 * g + 1)}) >> {s}) & 31) + 1, 1)" for g in range(8) for s in (15, 10, 5, 0))
    return f"""WITH p AS (SELECT page_id, coalesce(html, '') AS html, sha1(coalesce(html, '')) AS h FROM pages), g AS (SELECT html, max(page_id) AS top FROM p GROUP BY 1)
    SELECT page_id, octet_length(encode(html)) AS payload_bytes, {letters} AS payload_digest, CASE WHEN top IS NULL OR page_id = top THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id <> top OR page_id IS NULL THEN top END AS refers_to FROM p JOIN g USING (html)"""


def oracle_sql() -> dict[str, str]:
    return {"op2_near_duplicates": op2(), "op6_substring_dedup": op6(), "op7_url_filter": op7(), "op8_quality_rules": op8(), "op9_warc_archive": op9()}
