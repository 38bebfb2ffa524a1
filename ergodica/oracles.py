"""DuckDB SQL for the registered queries: closed forms, recursions, and plain relational equivalents."""

from __future__ import annotations


def _cyclic(table: str, key: str, order: str, state: str) -> str:
    """src, dst of the closed succession."""
    return f"""SELECT {state} AS src, coalesce(lead({state}) OVER w, first_value({state}) OVER (PARTITION BY {key} ORDER BY {order})) AS dst
        FROM {table} WINDOW w AS (PARTITION BY {key} ORDER BY {order})"""


EVENT_SHARE = "SELECT event_type AS label, round(count(*) * 1.0 / (SELECT count(*) FROM events), 6) AS pi FROM events GROUP BY 1"
HOUR = "CAST(floor(epoch(ts) / 3600) - 473352 AS BIGINT)"  # hours since 2024-01-01
HOUR_SHARE = f"SELECT {HOUR} AS state, round(count(*) * 1.0 / (SELECT count(*) FROM events), 6) AS pi FROM events GROUP BY 1"

EVENT_EDGES = f"""pairs AS ({_cyclic("events", "user_id", "ts, event_id", "event_type")}),
    c AS (SELECT src, dst, count(*) AS w FROM pairs GROUP BY ALL),
    e AS (SELECT src, dst, w * 1.0 / sum(w) OVER (PARTITION BY src) AS prob FROM c)"""


HOUR_EDGES = f"""pairs AS ({_cyclic("(SELECT *, " + HOUR + " AS hour FROM events)", "user_id", "ts, event_id", "hour")}),
    c AS (SELECT src, dst, count(*) AS w FROM pairs GROUP BY ALL),
    e AS (SELECT src, dst, w * 1.0 / sum(w) OVER (PARTITION BY src) AS prob FROM c)"""


def _regional(eps: str) -> str:
    return f"""f AS (SELECT CAST(c_nationkey AS BIGINT) AS src, CAST(s_nationkey AS BIGINT) AS dst, count(*) AS n
        FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY ALL),
    c AS (SELECT f.src, f.dst, a.n_regionkey AS ra, b.n_regionkey AS rb, CASE WHEN a.n_regionkey = b.n_regionkey THEN n * 1.0 ELSE n * CAST({eps} AS DOUBLE) END AS w
        FROM f JOIN nation a ON a.n_nationkey = f.src JOIN nation b ON b.n_nationkey = f.dst),
    e AS (SELECT src, dst, w / sum(w) OVER (PARTITION BY src) AS prob FROM c)"""


def _steps(edges: str, steps: int, follow: str = "1.0", pref: str | None = None, digits: int = 9, column: str = "x", name: str = "state") -> str:
    """Fixed-step iteration from the uniform vector over ``e``."""
    rest = pref or "(SELECT state, 1.0 / (SELECT count(*) FROM s) AS share FROM s)"
    jump = "" if follow == "1.0" else f"UNION ALL SELECT state, (1 - {follow}) * share FROM {rest} p"
    parts = []
    for k in range(1, steps + 1):
        parts.append(f"x{k} AS MATERIALIZED (SELECT state, sum(m) AS x FROM (SELECT dst AS state, {follow} * x * prob AS m FROM x{k - 1} JOIN e ON e.src = x{k - 1}.state {jump}) GROUP BY 1)")
    return f"""WITH {edges}, s AS (SELECT src AS state FROM e UNION SELECT dst FROM e), x0 AS (SELECT state, 1.0 / (SELECT count(*) FROM s) AS x FROM s),
    {", ".join(parts)} SELECT state AS {name}, round(x, {digits}) AS {column} FROM x{steps}"""


def _degree(weights: str, state: str = "state") -> str:
    """Degree share of the undirected weights u(src, dst, w) made by ``weights``."""
    return f"WITH {weights}, d AS (SELECT src AS s, w FROM u UNION ALL SELECT dst, w FROM u) SELECT s AS {state}, round(sum(w) * 1.0 / (SELECT sum(w) FROM d), 6) AS pi FROM d GROUP BY 1"


KNN = """v AS (SELECT vec_id AS id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings),
    p AS (SELECT a.id AS src, b.id AS dst, round(list_cosine_similarity(a.v, b.v), 12) AS w FROM v a JOIN v b ON a.id <> b.id),
    t AS (SELECT src, dst, w FROM p QUALIFY row_number() OVER (PARTITION BY src ORDER BY w DESC, dst) <= 5),
    u AS (SELECT src, dst, max(w) AS w FROM (SELECT src, dst, w FROM t UNION ALL SELECT dst, src, w FROM t) GROUP BY ALL)"""
LINKS = r"""l AS (SELECT 'h:' || regexp_extract(url, '^[^:]+://([^/?#]*)', 1) AS src, 'p:' || unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS dst FROM pages),
    u AS (SELECT src, dst, count(*) AS w FROM l GROUP BY ALL)"""
LINK_EDGES = f"{LINKS}, b AS (SELECT src, dst, w FROM u UNION ALL SELECT dst, src, w FROM u), e AS (SELECT src, dst, w * 1.0 / sum(w) OVER (PARTITION BY src) AS prob FROM b)"
# one jump from hosts to targets; targets are dangling, so their mass, like the restarts, is spread over all states: closed form by one number
DIRECTED = f"""WITH {LINKS}, s AS (SELECT src AS state FROM u UNION SELECT dst FROM u), n AS (SELECT count(*) AS n FROM s), e AS (SELECT src, dst, w * 1.0 / sum(w) OVER (PARTITION BY src) AS prob FROM u),
    i AS (SELECT dst AS state, sum(prob) AS p FROM e GROUP BY 1), y AS (SELECT state, 1 + 0.85 * coalesce(p, 0) AS y FROM s LEFT JOIN i USING (state))
    SELECT state AS label, round(y / (SELECT sum(y) FROM y), 6) AS pi FROM y"""
MONTHS = """m AS (SELECT CAST(year(o_orderdate) * 12 + month(o_orderdate) AS BIGINT) AS k, count(*) AS n FROM orders GROUP BY 1),
    u AS (SELECT a.k AS src, b.k AS dst, a.n + b.n AS w FROM m a JOIN m b ON b.k = a.k + 1)"""
WORDS = r"""t AS (SELECT doc_id, regexp_extract_all(lower(coalesce(text, '')), '[a-z0-9_\x{80}-\x{ffff}]+') AS w FROM documents),
    f AS (SELECT row_number() OVER () AS d, w FROM t WHERE len(w) > 0),
    q AS (SELECT unnest(w) AS src, unnest(list_concat(w[2:], w[1:1])) AS dst FROM f),
    o AS (SELECT DISTINCT src FROM q WHERE src <> dst),
    k AS (SELECT q.src FROM q JOIN o USING (src))"""
FIVE = f"""pairs AS ({_cyclic("orders", "o_custkey", "o_orderdate, o_orderkey", "o_orderpriority")}), b AS (SELECT src, dst FROM pairs UNION ALL SELECT dst, src FROM pairs),
    g AS (SELECT src, dst, left(src, 1) IN ('3', '4') AS x, left(dst, 1) IN ('3', '4') AS y, count(*) AS n FROM b GROUP BY ALL),
    w AS (SELECT src, dst, n * CAST(CASE WHEN x <> y THEN 6e-4 WHEN x AND src = dst THEN 0 WHEN x THEN 9 WHEN src = dst THEN 4 ELSE 1 END AS DOUBLE) AS w FROM g),
    e AS (SELECT src, dst, w / sum(w) OVER (PARTITION BY src) AS prob FROM w)"""


def _sites(channels: int) -> str:
    """s: the release sites of so many successive events."""
    kinds = ", ".join(f"lead(k, {j}) OVER w AS k{j}" for j in range(channels))
    many = ", ".join(f"{' + '.join(f'(k{j} = {i})::INT' for j in range(channels))} AS {c}" for i, c in enumerate("coiq"))
    return f"""k AS (SELECT *, (dense_rank() OVER (ORDER BY event_type) - 1) % 4 AS k FROM events), r AS (SELECT hour(ts) AS n, {kinds} FROM k WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
        s AS (SELECT DISTINCT {many}, n FROM r WHERE k{channels - 1} IS NOT NULL)"""


PARTS = "l_orderkey", "l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice, l_discount, l_tax, l_shipdate"


def _visits(table: str, column: str, label: str = "label", where: str = "") -> str:
    return f"SELECT {column} AS {label}, round(count(*) * 1.0 / (SELECT count(*) FROM {table} {where}), 6) AS pi FROM {table} {where} GROUP BY 1"


def _values(rows: list[tuple], names: str) -> str:
    return f"SELECT * FROM (VALUES {', '.join(str(r) for r in rows)}) AS t({names})"


FLOW = """f AS (SELECT CAST(c_nationkey AS BIGINT) AS src, CAST(s_nationkey AS BIGINT) AS dst, count(*) * 1.0 AS w
        FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY ALL),
    g AS (SELECT f.*, CAST(a.n_regionkey AS BIGINT) AS src_region, CAST(b.n_regionkey AS BIGINT) AS dst_region FROM f JOIN nation a ON a.n_nationkey = f.src JOIN nation b ON b.n_nationkey = f.dst)"""


#: What the experiments are to show; every claim must hold.
CLAIMS = {
    "check_ablation": [
        "checks every 10",
        "checks every 100",
    ],
    "crowded_savings": [
        "steps fall with the width",
        "no width above 1 saves products",
        "a window of 4 on one column saves 40 to 60 per cent",
        "depths 8 and 16 save at most 5 per cent more",
        "a window saves products at widths 2 to 8 too",
    ],
    "extraction_ablation": [
        "eigen and Schur within two checks of the least residual",
        "all ranks are full",
    ],
    "five_state_counts": [
        "residual: width 2 takes about a third of the steps of the power method, width 3 under 100",
        "distance: within a tenth of the prediction at widths 1 and 2, under 80 steps at width 3",
        "a window of 3, 4, 5 on one column takes under 100 products, of 5 under 8",
    ],
    "grid_sweep": [
        "five columns need at most 15 steps, four over 1,000",
        "five columns in all, by width and depth, need at most 25 steps",
        "a deeper window never needs two checks more",
    ],
    "image_ablation": [
        "both converge, explicit images in no more steps than one check above",
        "a pass more at each check",
    ],
    "savings_cube": [
        "the cube has 2 by 2 cells and 18 rows",
        "its total is the best cell",
    ],
    "similarity_savings": [
        "no width saves products",
        "a window of 8 on one column does not cost any",
    ],
    "sweep_savings": [
        "steps fall with every width",
        "the best width is 8, 16 or 32 and saves over 80 per cent of the products",
        "width 128 saves less than the best",
        "a window of 4 on one column saves over half, 8 and 16 at most 5 per cent more",
        "a window on a block saves more than either",
        "orthonormal columns at every step save no more products than the plain block",
    ],
    "width_sweep": [
        "every run converges",
        "steps never rise with the width",
        "products are steps times width",
    ],
}


def oracle_sql() -> dict[str, str]:
    found = {k: EVENT_SHARE for k in ("event_power", "event_block_s2", "event_window_t3", "event_window_block", "event_subspace", "event_block_distributed", "event_window_distributed")}
    found |= {k: HOUR_SHARE for k in ("hour_block_s16", "hour_window_s4_t4", "hour_local_kernel", "hour_block_distributed")}
    found |= {k: _steps(_regional("0.1"), 60, digits=6, column="pi") for k in ("regional_block_s5", "regional_window", "regional_block_distributed", "regional_laid_out")}
    found |= {
        "event_steps_fixed": _steps(EVENT_EDGES, 5, name="label"),
        "regional_steps_fixed": _steps(_regional("0.1"), 10),
        "knn_block": _degree(KNN.replace("u AS (SELECT src, dst, max(w)", "uu AS (SELECT src, dst, max(w)") + ", u AS (SELECT src, dst, w FROM uu WHERE src < dst)"),
        "host_rank_undirected": _degree(LINKS, "label"),
        "host_rank_teleport": _steps(LINK_EDGES, 110, "0.85", digits=6, column="pi", name="label"),
        "host_rank_teleport_distributed": _steps(LINK_EDGES, 10, "0.85", digits=6, name="label"),
        "bipartite_lazy": _degree("u AS (SELECT o_custkey * 2 AS src, l_suppkey * 2 + 1 AS dst, count(*) AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL)"),
        "supplier_two_step": _visits("lineitem", "l_suppkey", "state"),
        "word_chain_top100": f"WITH {WORDS} SELECT src AS label, round(count(*) * 1.0 / (SELECT count(*) FROM k), 6) AS pi FROM k GROUP BY 1 ORDER BY count(*) DESC, src LIMIT 100",
        "role_chain": _visits("conversations", "role"),
        "priority_chain": _visits("orders", "o_orderpriority"),
        "month_ladder": _degree(MONTHS),
        "json_props_chain": _visits("(SELECT json_extract_string(props, '$.k') AS k FROM events)", "k", where="WHERE k IS NOT NULL"),
        "part_chain": _visits("lineitem", "l_partkey", "state"),
        "user_batch": """SELECT user_id, (SELECT count(DISTINCT event_type) FROM events b WHERE b.event_type < e.event_type) AS state, round(count(*) * 1.0 / sum(count(*)) OVER (PARTITION BY user_id), 6) AS pi
            FROM events e GROUP BY user_id, event_type""",
        "grouped_stationary": """WITH c AS (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY ALL)
            SELECT user_id, CAST(row_number() OVER (PARTITION BY user_id ORDER BY event_type) - 1 AS INTEGER) AS at, round(n * 1.0 / sum(n) OVER (PARTITION BY user_id), 6) AS pi FROM c""",
        "sql_stationary": """SELECT (SELECT count(DISTINCT event_type) FROM events b WHERE b.event_type < e.event_type) AS state, round(count(*) * 1.0 / (SELECT count(*) FROM events WHERE user_id = 0), 6) AS pi
            FROM events e WHERE user_id = 0 GROUP BY event_type""",
        "five_state_pi": f"WITH {FIVE} SELECT row_number() OVER (ORDER BY src) - 1 AS state, round(sum(w) / (SELECT sum(w) FROM w), 6) AS pi FROM w GROUP BY src",
        "spectrum_leading": _values([(i, True) for i in range(1, 5)], "rank, agrees"),
        "five_state_leading": _values([(1, 1.0), (2, 0.9998), (3, 0.9996)], "rank, magnitude"),
        "knn_lsh_recall": f"WITH {KNN} SELECT count(*) AS pairs, true AS enough FROM u",
        "five_state_extractions": _values([(m, True) for m in ("ritz_schur", "ritz_eig", "min_residual", "gram")], "method, settled"),
        "five_state_rates": "SELECT 3 AS width, true AS as_predicted",
        "accuracy_measures": f"""WITH z AS ({_steps(HOUR_EDGES, 10)}), v AS (SELECT {HOUR} AS state, count(*) * 1.0 / (SELECT count(*) FROM events) AS p FROM events GROUP BY 1),
            g AS (SELECT coalesce(x, 0) - coalesce(p, 0) AS g FROM z FULL JOIN v USING (state)) SELECT round(sum(abs(g)), 6) AS l1, round(sqrt(sum(g * g)), 6) AS l2, round(max(abs(g)), 6) AS max_abs, round(sum(abs(g)) / 2, 6) AS total_variation FROM g""",
        "storage_ablation": _values([(k, 24, 1.0) for k in ("cached", "scan", "matrix_free")], "storage, matvecs, mass"),
        "layout_ablation": _values([("rows", 1.0), ("columns", 1.0)], "layout, mass"),
        "spectrum_recommend": _values([(i, i == 5) for i in range(1, 7)], "width, recommended"),
        "planner_choices": """SELECT chain, states, width, CASE WHEN states * (8 * width + 16) <= 268435456 THEN 'broadcast' ELSE 'shuffle_hash' END AS "join" FROM (VALUES (1), (16), (1024)) AS w(width),
            (SELECT 'l_suppkey' AS chain, count(DISTINCT l_suppkey) AS states FROM lineitem UNION ALL SELECT 'l_partkey', count(DISTINCT l_partkey) FROM lineitem UNION ALL SELECT 'l_orderkey', count(DISTINCT l_orderkey) FROM lineitem)""",
        "components": f"""WITH RECURSIVE {LINKS}, b AS (SELECT src, dst FROM u UNION SELECT dst, src FROM u), r AS (SELECT src AS a, src AS z FROM b UNION SELECT r.a, b.dst FROM r JOIN b ON b.src = r.z),
            c AS (SELECT a, min(z) AS c FROM r GROUP BY 1), n AS (SELECT c, count(*) AS size FROM c GROUP BY 1) SELECT size, count(*) AS n FROM n GROUP BY 1""",
        "release_site_solved": "SELECT range AS ions, round(1.0 / 31, 6) AS pi FROM range(31)",
        "release_site_full": "SELECT range AS ions, round(0.9 * pow(0.1, range), 6) AS pi FROM range(8)",
        "release_site_source": f"""WITH {_sites(2)}
            SELECT count(*) AS n_states, CAST(sum(1 + 2 * ((c > 0)::INT + (o > 0)::INT + (i > 0)::INT + (q > 0)::INT) + (n < 23)::INT + (n > 0)::INT) AS BIGINT) AS n_moves, count(*) * 1.0 AS total FROM s""",
        "host_rank_directed": DIRECTED,
        "five_state_eigen": f"""WITH {FIVE}, p AS (SELECT a.src, b.dst, sum(a.prob * b.prob) AS prob FROM e a JOIN e b ON a.dst = b.src GROUP BY ALL), q AS (SELECT a.src, b.dst, sum(a.prob * b.prob) AS prob FROM p a JOIN e b ON a.dst = b.src GROUP BY ALL)
            SELECT 1 AS power, round(sum(prob), 6) AS total FROM e WHERE src = dst UNION ALL SELECT 2, round(sum(prob), 6) FROM p WHERE src = dst UNION ALL SELECT 3, round(sum(prob), 6) FROM q WHERE src = dst
            UNION ALL SELECT 4, round(sum(a.prob * b.prob), 6) FROM p a JOIN p b ON a.src = b.dst AND a.dst = b.src UNION ALL SELECT 5, round(sum(a.prob * b.prob), 6) FROM p a JOIN q b ON a.src = b.dst AND a.dst = b.src""",
        "predicted_steps": "SELECT l_suppkey, (n - 1) / n AS modulus, round(ln(1e-10) / ln((n - 1) / n), 4) AS steps FROM (SELECT l_suppkey, CAST(count(*) AS DOUBLE) AS n FROM lineitem GROUP BY 1) WHERE n > 1",
        "start_blocks": _values([(k, j, 1.0, 4) for k in ("random", "indicator") for j in range(4)], "kind, column_no, mass, rank"),
        "residual_of_frequency": """WITH o AS (SELECT event_type AS src, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS dst FROM events),
            c AS (SELECT src, dst, count(*) AS w FROM o WHERE dst IS NOT NULL GROUP BY ALL), e AS (SELECT src, dst, w * 1.0 / sum(w) OVER (PARTITION BY src) AS prob FROM c),
            v AS (SELECT event_type AS s, count(*) * 1.0 / (SELECT count(*) FROM events) AS x FROM events GROUP BY 1),
            y AS (SELECT dst AS s, sum(x * prob) AS y FROM v JOIN e ON e.src = v.s GROUP BY 1)
            SELECT round(sqrt(sum((coalesce(y, 0) - coalesce(x, 0)) ** 2)) / sqrt(sum(coalesce(x, 0) ** 2)), 9) AS residual FROM v FULL JOIN y USING (s)""",
        "span_distance_two_vectors": """WITH a AS (SELECT c_nationkey AS k, count(*) * 1.0 AS a FROM customer GROUP BY 1), b AS (SELECT s_nationkey AS k, count(*) * 1.0 AS b FROM supplier GROUP BY 1),
            j AS (SELECT coalesce(a, 0) AS a, coalesce(b, 0) AS b FROM a FULL JOIN b USING (k)), d AS (SELECT sum(a * a) AS aa, sum(b * b) AS bb, sum(a * b) AS ab FROM j)
            SELECT round(sqrt(sum((a / sqrt(aa) - b / sqrt(bb) * (ab / sqrt(aa * bb))) ** 2)), 9) AS distance FROM j, d""",
        "chain_edges_event": f"WITH {EVENT_EDGES} SELECT src, dst, round(prob, 6) AS prob FROM e",
        "sliced_succession": f"WITH {EVENT_EDGES} SELECT src, dst, w FROM c",
        "observed_pass": f"WITH {_regional('0.1')} SELECT count(*) AS n_edges FROM e",
        "chain_edges_regional": f"WITH {_regional('0.1')} SELECT src, dst, round(prob, 6) AS prob FROM e",
        "encoded_states": "SELECT row_number() OVER (ORDER BY event_type) - 1 AS state, event_type AS label FROM (SELECT DISTINCT event_type FROM events)",
        "row_sums": f"WITH {_regional('0.01')} SELECT src, round(sum(prob), 6) AS total, count(*) AS exits FROM e GROUP BY 1",
        "validated": f"WITH {_regional('0.01')} SELECT count(DISTINCT src) AS n_rows, 0 AS n_off, 0 AS n_bad, (SELECT count(*) FROM (SELECT dst FROM e EXCEPT SELECT src FROM e)) AS n_dangling FROM e",
        "dangling_states": f"WITH {LINKS} SELECT dst AS label FROM u EXCEPT SELECT src FROM u",
        "dangling_repaired": f"""WITH {LINKS}, n AS (SELECT count(*) AS n FROM (SELECT dst FROM u EXCEPT SELECT src FROM u))
            SELECT 'none' AS policy, CAST(n AS INTEGER) AS n_left FROM n UNION ALL SELECT * FROM (VALUES ('self_loop', 0), ('drop', 0), ('uniform', 0)) AS t(policy, n_left)""",
        "lazy_edges": f"WITH {_regional('0.1')}, a AS (SELECT src, dst, prob / 2 AS p FROM e UNION ALL SELECT DISTINCT s, s, 0.5 FROM (SELECT src AS s FROM e UNION SELECT dst FROM e)) SELECT src, dst, round(sum(p), 6) AS prob FROM a GROUP BY ALL",
        "two_step_edges": """WITH c AS (SELECT l_suppkey AS s, l_partkey AS p, count(*) AS w FROM lineitem GROUP BY ALL), q AS (SELECT s, p, w * 1.0 / sum(w) OVER (PARTITION BY p) AS q FROM c),
            d AS (SELECT c.s AS src, q.s AS dst, sum(w * q) AS w FROM c JOIN q USING (p) GROUP BY ALL) SELECT src, dst, round(w / sum(w) OVER (PARTITION BY src), 6) AS prob FROM d""",
        "composed_edges": f"WITH {_regional('0.1')} SELECT a.src, b.dst, round(sum(a.prob * b.prob), 6) AS prob FROM e a JOIN e b ON a.dst = b.src GROUP BY ALL",
        "reverse_chain": f"WITH {EVENT_EDGES}, v AS (SELECT src AS s, sum(w) AS n FROM c GROUP BY 1) SELECT e.dst AS src, e.src AS dst, round(a.n * prob / b.n, 6) AS prob FROM e JOIN v a ON a.s = e.src JOIN v b ON b.s = e.dst",
        "detailed_balance": f"""WITH {EVENT_EDGES}, f AS (SELECT src, dst, w * 1.0 / (SELECT sum(w) FROM c) AS f FROM c), g AS (SELECT src, dst, f FROM f UNION ALL SELECT dst, src, -f FROM f)
            SELECT src, dst, round(sum(f), 6) + 0.0 AS gap FROM g GROUP BY ALL""",
        "periods": _values([("cycle_6", 6), ("ladder", 1), ("hosts", 2)], "chain, period"),
        "strong_components": "SELECT CAST(c AS BIGINT) AS component, n AS size FROM (VALUES (0, (SELECT count(DISTINCT role) FROM conversations)), (100, 2)) AS t(c, n)",
        "release_site_states": " UNION ALL ".join(f"(WITH {_sites(n)} SELECT {n} AS channels, 23 AS capacity, {size} AS n_states, count(*) AS n_met, 0 AS n_unknown FROM s)" for n, size in ((1, 96), (2, 240), (3, 480))),
        "matrix_free_equal": "SELECT 0 AS n_different",
        "transition_cube": f"WITH {FLOW} SELECT src_region, dst_region, sum(w) AS w, grouping_id(src_region, dst_region) AS level FROM g GROUP BY CUBE (src_region, dst_region)",
        "transition_rollup": f"WITH {FLOW} SELECT src_region, src, sum(w) AS w, count(*) AS n FROM g GROUP BY ROLLUP (src_region, src)",
        "pivot_flow": f"WITH {FLOW} SELECT src_region, {', '.join(f'sum(w) FILTER (dst_region = {i}) AS to_{i}' for i in range(5))} FROM g GROUP BY 1",
        "top_states": f"SELECT {HOUR} AS state, round(count(*) * 1.0 / (SELECT count(*) FROM events), 6) AS pi FROM events GROUP BY 1 ORDER BY count(*) DESC, 1 LIMIT 20",
        "top_per_region": f"WITH {FLOW}, t AS (SELECT dst_region, dst AS state, sum(w) AS w FROM g GROUP BY ALL) SELECT *, row_number() OVER (PARTITION BY dst_region ORDER BY w DESC, state) AS rank FROM t QUALIFY rank <= 2",
        "running_mass": f"WITH c AS (SELECT {HOUR} AS state, count(*) AS n FROM events GROUP BY 1) SELECT state, round(sum(n) OVER (ORDER BY n DESC, state) * 1.0 / sum(n) OVER (), 6) AS running FROM c",
        "state_setops": """WITH c AS (SELECT c_nationkey AS s FROM customer), p AS (SELECT s_nationkey AS s FROM supplier WHERE s_acctbal > 0)
            SELECT 'union_set' AS op, (SELECT count(*) FROM (SELECT s FROM c UNION SELECT s FROM p)) AS n UNION ALL SELECT 'union_all', (SELECT count(*) FROM (SELECT s FROM c UNION ALL SELECT s FROM p))
            UNION ALL SELECT 'intersect_set', (SELECT count(*) FROM (SELECT s FROM c INTERSECT SELECT s FROM p)) UNION ALL SELECT 'intersect_all', (SELECT count(*) FROM (SELECT s FROM c INTERSECT ALL SELECT s FROM p))
            UNION ALL SELECT 'except_set', (SELECT count(*) FROM (SELECT s FROM c EXCEPT SELECT s FROM p)) UNION ALL SELECT 'except_all', (SELECT count(*) FROM (SELECT s FROM c EXCEPT ALL SELECT s FROM p))""",
        "semi_anti_states": "SELECT 'entered' AS kind, count(*) FILTER (c_custkey IN (SELECT o_custkey FROM orders)) AS n FROM customer UNION ALL SELECT 'never', count(*) FILTER (c_custkey NOT IN (SELECT o_custkey FROM orders)) FROM customer",
        "within_succession": """WITH o AS (SELECT event_type AS src, lead(event_type) OVER w AS dst, epoch_us(lead(ts) OVER w) - epoch_us(ts) AS gap FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts))
            SELECT src, dst, count(*) AS w FROM o WHERE gap <= 21600000000 GROUP BY ALL""",
        "interval_pairs": "SELECT l.user_id, l.event_type, count(*) AS n FROM events l JOIN events r ON l.user_id = r.user_id AND l.event_type <> r.event_type AND r.ts > l.ts AND epoch_us(r.ts) <= epoch_us(l.ts) + 86400000000 GROUP BY ALL",
        "asof_succession": """WITH k AS (SELECT event_type AS kind, coalesce(lead(event_type) OVER (ORDER BY event_type), first_value(event_type) OVER (ORDER BY event_type)) AS other FROM (SELECT DISTINCT event_type FROM events)),
            l AS (SELECT e.*, k.other FROM events e JOIN k ON k.kind = e.event_type) SELECT l.event_id, r.event_id AS last_event FROM l ASOF LEFT JOIN events r ON l.user_id = r.user_id AND l.other = r.event_type AND l.ts >= r.ts""",
        "trust_rank": _steps("""t AS (SELECT 'l:' || coalesce(lang, '?') AS src, 's:' || coalesce(source, '?') AS dst, count(*) AS w FROM documents GROUP BY ALL), b AS (SELECT src, dst, w FROM t UNION ALL SELECT dst, src, w FROM t),
            e AS (SELECT src, dst, w * 1.0 / sum(w) OVER (PARTITION BY src) AS prob FROM b), g AS (SELECT DISTINCT doc_id FROM labels WHERE quality = 1 AND toxic = 0),
            pr AS (SELECT 's:' || coalesce(source, '?') AS state, count(*) * 1.0 / sum(count(*)) OVER () AS share FROM documents JOIN g USING (doc_id) GROUP BY 1)""", 10, "0.85", "pr", 6, name="label"),
        "similarity_restart": _steps(f"{KNN}, e AS (SELECT src, dst, w / sum(w) OVER (PARTITION BY src) AS prob FROM u), pr AS (SELECT id AS state, 0.2 AS share FROM v WHERE id < 5)", 10, "0.85", "pr", 6),
        "stream_succession": "WITH o AS (SELECT event_type AS src, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS dst FROM events) SELECT src, dst, count(*) AS w FROM o WHERE dst IS NOT NULL GROUP BY ALL",
    }
    found |= {k: _values([(c, True) for c in v], "claim, holds") for k, v in CLAIMS.items()}
    found["knn_window"] = found["knn_block"]
    found["host_rank_distributed"] = found["host_rank_teleport"]
    found["sql_stationary_users"] = found["user_batch"]
    return found
