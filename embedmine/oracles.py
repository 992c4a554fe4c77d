"""Equivalent SQL of the mining queries, written from definitions (joins and sets), not from the engine."""

from __future__ import annotations

from .queries import DEEP, NO_MAXIMUM, PATH_LABELS, THETA

_EDGES = {
    "similar": "SELECT a.vec_id AS src, b.vec_id AS dst FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id WHERE list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])) >= 0.3",
    "copart": "SELECT a.l_partkey AS src, b.l_partkey AS dst FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) a JOIN (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey GROUP BY ALL HAVING count(*) >= 2",
    "docs": """SELECT DISTINCT a.doc_id AS src, b.doc_id AS dst FROM held a JOIN held b ON a.line = b.line AND a.doc_id < b.doc_id""",
    "custsupp": "SELECT least(c, s) AS src, greatest(c, s) AS dst, min(p) AS elabel FROM (SELECT 2 * o_custkey AS c, 2 * l_suppkey + 1 AS s, o_orderpriority AS p FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_returnflag = 'R' AND l_quantity >= 45) GROUP BY ALL",
    "coactive": "SELECT a.user_id AS src, b.user_id AS dst FROM events a JOIN events b ON a.event_type = b.event_type AND a.user_id < b.user_id AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 600000000 GROUP BY ALL",
    "geo": "SELECT least(a, b) AS src, greatest(a, b) AS dst FROM (SELECT 4 * n_regionkey AS a, 4 * n_nationkey + 1 AS b FROM nation UNION SELECT 4 * c_nationkey + 1, 4 * c_custkey + 2 FROM customer UNION SELECT 4 * s_nationkey + 1, 4 * s_suppkey + 3 FROM supplier)",
    "weblink": "SELECT DISTINCT least(a, b) AS src, greatest(a, b) AS dst FROM (SELECT 2 * page_id AS a, 2 * dense_rank() OVER (ORDER BY target) + 1 AS b FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS target FROM pages))",
    "conversations": "SELECT a AS src, b AS dst FROM (SELECT conv_id * 100000 + turn AS a, conv_id * 100000 + lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS b FROM (SELECT DISTINCT conv_id, turn FROM conversations)) WHERE b IS NOT NULL",
}
_BEFORE = {
    "docs": """line AS MATERIALIZED (SELECT DISTINCT doc_id, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) >= 20),
held AS MATERIALIZED (SELECT * FROM line WHERE line IN (SELECT line FROM line GROUP BY line HAVING count(*) BETWEEN 2 AND 12)),
""",
}
_LABELS = {
    "similar": "SELECT vec_id AS vid, CAST(label AS VARCHAR) AS label FROM embeddings",
    "copart": "SELECT p_partkey AS vid, p_type AS label FROM part",
    "docs": "SELECT doc_id AS vid, lang AS label FROM documents",
    "custsupp": "SELECT 2 * c_custkey AS vid, n_name AS label FROM customer JOIN nation ON c_nationkey = n_nationkey UNION ALL SELECT 2 * s_suppkey + 1, n_name FROM supplier JOIN nation ON s_nationkey = n_nationkey",
    "coactive": "SELECT user_id AS vid, event_type AS label FROM (SELECT user_id, event_type, row_number() OVER (PARTITION BY user_id ORDER BY count(*) DESC, event_type) AS r FROM events GROUP BY user_id, event_type) WHERE r = 1",
    "geo": "SELECT vid, CASE vid % 4 WHEN 0 THEN 'region' WHEN 1 THEN 'nation' WHEN 2 THEN 'customer' ELSE 'supplier' END AS label FROM deg",
    "weblink": "SELECT 2 * page_id AS vid, regexp_extract(url, '://([^/]+)', 1) AS label FROM pages UNION ALL SELECT 1, 'path'",
    "conversations": "SELECT conv_id * 100000 + turn AS vid, min(role) AS label FROM conversations GROUP BY ALL",
}


def graph(name: str) -> str:
    """CTEs e (src, dst, eid), adj (vid, nbr, eid), deg (vid, d), lab (vid, label)."""
    return f"""WITH {_BEFORE.get(name, '')}e0 AS MATERIALIZED ({_EDGES[name]}),
e AS MATERIALIZED (SELECT *, row_number() OVER (ORDER BY src, dst) - 1 AS eid FROM e0),
adj AS MATERIALIZED (SELECT src AS vid, dst AS nbr, eid FROM e UNION ALL SELECT dst, src, eid FROM e),
deg AS MATERIALIZED (SELECT vid, count(*) AS d FROM adj GROUP BY vid),
lab AS MATERIALIZED ({_LABELS[name]})"""


def longs(*columns: str) -> str:
    return ", ".join(f"CAST({c} AS BIGINT) AS {c}" for c in columns)


_TRI = "tri AS MATERIALIZED (SELECT a.src AS x, a.dst AS y, b.dst AS z FROM e a JOIN e b ON a.dst = b.src JOIN e c ON c.src = a.src AND c.dst = b.dst)"
_SETS3 = "s3 AS MATERIALIZED (SELECT DISTINCT q[1] AS x, q[2] AS y, q[3] AS z FROM (SELECT list_sort([p.vid, p.nbr, r.nbr]) AS q FROM adj p JOIN adj r ON p.nbr = r.vid WHERE p.vid <> r.nbr))"
_SETS4 = "s4 AS MATERIALIZED (SELECT DISTINCT list_sort([x, y, z, nbr]) AS q FROM (SELECT x, y, z, unnest([x, y, z]) AS vid FROM s3) JOIN adj USING (vid) WHERE nbr NOT IN (x, y, z))"
_DEGS4 = "d4 AS MATERIALIZED (SELECT q, list_sort(list(c)) AS l FROM (SELECT q, v, count(*) AS c FROM (SELECT q, unnest(q) AS v FROM s4) JOIN adj ON adj.vid = v WHERE list_contains(q, nbr) GROUP BY q, v) GROUP BY q)"
_MOTIF3 = """SELECT CAST(k AS BIGINT) AS k, CAST(n_edges AS BIGINT) AS n_edges, degs, CAST(n AS BIGINT) AS n FROM (
SELECT 3 AS k, 2 AS n_edges, '1-1-2' AS degs, (SELECT sum(d * (d - 1) // 2) FROM deg) - 3 * (SELECT count(*) FROM tri) AS n
UNION ALL SELECT 3, 3, '2-2-2', (SELECT count(*) FROM tri)) WHERE n > 0"""
_MOTIF4 = "SELECT CAST(4 AS BIGINT) AS k, CAST(list_sum(l) / 2 AS BIGINT) AS n_edges, array_to_string(l, '-') AS degs, count(*) AS n FROM d4 GROUP BY ALL"
# Canonical visiting order of a connected set x < y < z.
_ORDER3 = """f3 AS MATERIALIZED (SELECT x AS w0, CASE WHEN xy THEN y ELSE z END AS w1, CASE WHEN xy THEN z ELSE y END AS w2, CAST(xy AS INT) + CAST(xz AS INT) + CAST(yz AS INT) AS n_edges, xy, xz, yz FROM (
SELECT x, y, z, EXISTS (SELECT 1 FROM e WHERE src = x AND dst = y) AS xy, EXISTS (SELECT 1 FROM e WHERE src = x AND dst = z) AS xz, EXISTS (SELECT 1 FROM e WHERE src = y AND dst = z) AS yz FROM s3))"""
_ADJL = "al AS MATERIALIZED (SELECT adj.*, a.label AS vl, b.label AS nl FROM adj JOIN lab a ON a.vid = adj.vid JOIN lab b ON b.vid = adj.nbr)"
_FSM1 = "p1 AS MATERIALIZED (SELECT vl AS la, nl AS lb, least(count(DISTINCT vid), count(DISTINCT nbr)) AS support, count(DISTINCT eid) AS n FROM al WHERE vl <= nl GROUP BY ALL)"
_FSM2 = "m2 AS MATERIALIZED (SELECT a.vid AS x, a.nbr AS c, b.nbr AS y, a.vl AS la, a.nl AS lc, b.nl AS lb, least(a.eid, b.eid) AS e1, greatest(a.eid, b.eid) AS e2 FROM al a JOIN al b ON a.nbr = b.vid AND a.vid <> b.nbr WHERE a.vl <= b.nl),\np2 AS MATERIALIZED (SELECT lc, la, lb, least(count(DISTINCT x), count(DISTINCT c), count(DISTINCT y)) AS support, count(DISTINCT (e1, e2)) AS n FROM m2 GROUP BY ALL)"
_CLIQ = {
    3: "k3 AS MATERIALIZED (SELECT a.src AS v1, a.dst AS v2, b.dst AS v3 FROM e a JOIN e b ON a.dst = b.src JOIN e c ON c.src = a.src AND c.dst = b.dst)",
    4: "k4 AS MATERIALIZED (SELECT v1, v2, v3, d.dst AS v4 FROM k3 JOIN e d ON d.src = v3 JOIN e f ON f.src = v1 AND f.dst = d.dst JOIN e g ON g.src = v2 AND g.dst = d.dst)",
    5: "k5 AS MATERIALIZED (SELECT v1, v2, v3, v4, d.dst AS v5 FROM k4 JOIN e d ON d.src = v4 JOIN e f ON f.src = v1 AND f.dst = d.dst JOIN e g ON g.src = v2 AND g.dst = d.dst JOIN e h ON h.src = v3 AND h.dst = d.dst)",
}


def build(name: str, *ctes: str, select: str) -> str:
    return ",\n".join([graph(name), *ctes]) + "\n" + select


def cliques(k: int) -> list[str]:
    return [_CLIQ[i] for i in range(3, k + 1)]


def vs(k: int) -> str:
    return longs(*[f"v{i + 1}" for i in range(k)])


def _maximal() -> str:
    parts = []
    for k in range(2, 6):
        v = ["src", "dst"] if k == 2 else [f"v{i + 1}" for i in range(k)]
        source = "e" if k == 2 else f"k{k}"
        joins = " AND ".join(f"EXISTS (SELECT 1 FROM adj b WHERE b.vid = {x} AND b.nbr = a.nbr)" for x in v[1:])
        parts.append(f"SELECT CAST({k} AS BIGINT) AS k, {' || chr(45) || '.join(v)} AS members FROM {source} WHERE NOT EXISTS (SELECT 1 FROM adj a WHERE a.vid = {v[0]} AND {joins})")
    return build("docs", *cliques(5), select="\nUNION ALL ".join(parts))


def _frequent_cliques() -> str:
    parts = []
    for k in (2, 3):
        v = ["src", "dst"] if k == 2 else ["v1", "v2", "v3"]
        source = "e" if k == 2 else "k3"
        parts.append(f"""SELECT CAST({k} AS BIGINT) AS k, lbls, min(c) AS support FROM (
SELECT lbls, label, count(DISTINCT v) AS c FROM (SELECT m, v, label, array_to_string(list_sort(list(label) OVER (PARTITION BY m)), '|') AS lbls FROM (SELECT [{', '.join(v)}] AS m, unnest([{', '.join(v)}]) AS v FROM {source}) JOIN lab ON vid = v) GROUP BY ALL) GROUP BY lbls HAVING min(c) >= 5""")
    return build("docs", _CLIQ[3], select="\nUNION ALL ".join(parts))


_P3 = """x3 AS MATERIALIZED (SELECT 'path' AS shape, p.vl || '|' || p.nl || '|' || r.vl || '|' || r.nl AS key, [p.vl, p.nl, r.vl, r.nl] AS ls, [p.vid, p.nbr, r.vid, r.nbr] AS q
FROM al p JOIN adj m ON m.vid = p.nbr JOIN al r ON r.vid = m.nbr WHERE p.vid <> r.vid AND p.nbr <> r.nbr AND p.vid <> r.nbr AND (p.vl, p.nl) <= (r.nl, r.vl)
UNION ALL SELECT 'star', a.vl || '|' || a.nl || '|' || b.nl || '|' || c.nl, [a.vl, a.nl, b.nl, c.nl], [a.vid, a.nbr, b.nbr, c.nbr]
FROM al a JOIN al b ON b.vid = a.vid JOIN al c ON c.vid = a.vid WHERE a.nbr <> b.nbr AND a.nbr <> c.nbr AND b.nbr <> c.nbr AND a.nl <= b.nl AND b.nl <= c.nl
UNION ALL SELECT 'triangle', a.vl || '|' || a.nl || '|' || b.nl, [a.vl, a.nl, b.nl], [a.vid, a.nbr, b.nbr]
FROM al a JOIN al b ON b.vid = a.nbr JOIN adj c ON c.vid = b.nbr AND c.nbr = a.vid WHERE a.vl <= a.nl AND a.nl <= b.nl),
g3 AS MATERIALIZED (SELECT shape, any_value(ls) AS ls, least(count(DISTINCT q[1]), count(DISTINCT q[2]), count(DISTINCT q[3]), CASE WHEN shape = 'triangle' THEN 1000000000 ELSE count(DISTINCT q[4]) END) AS support FROM x3 GROUP BY shape, key)"""


def _fsm3(name: str = "similar", least: int = 3) -> str:
    return build(
        name, _ADJL, _FSM1, _FSM2, _P3,
        select="""SELECT CAST(k AS BIGINT) AS k, CAST(n_edges AS BIGINT) AS n_edges, degs, lbls, CAST(support AS BIGINT) AS support FROM (
SELECT 2 AS k, 1 AS n_edges, '1-1' AS degs, array_to_string(list_sort([la, lb]), '|') AS lbls, support FROM p1
UNION ALL SELECT 3, 2, '1-1-2', array_to_string(list_sort([lc, la, lb]), '|'), support FROM p2
UNION ALL SELECT CASE shape WHEN 'triangle' THEN 3 ELSE 4 END, 3, CASE shape WHEN 'path' THEN '1-1-2-2' WHEN 'star' THEN '1-1-1-3' ELSE '2-2-2' END, array_to_string(list_sort(ls), '|'), support FROM g3) WHERE support >= """ + str(least),
    )


_STORE = "st AS MATERIALIZED (SELECT DISTINCT n_edges, unnest([0, 1]) AS level, unnest([w0, w1]) AS node, unnest([w1, w2]) AS next FROM f3)"
_LBL_PATH = ", ".join(f"'{x}'" for x in PATH_LABELS)


def oracle_sql() -> dict[str, str]:
    out: dict[str, str] = {}
    for name in _EDGES:
        out[f"graph_stats_{name}"] = build(name, select="SELECT (SELECT count(*) FROM deg) AS n_vertices, (SELECT count(*) FROM e) AS n_edges, (SELECT count(DISTINCT label) FROM lab) AS n_labels, round(CAST(2 * (SELECT count(*) FROM e) AS DOUBLE) / (SELECT count(*) FROM deg), 6) AS avg_degree")
    for name in ("similar", "copart", "custsupp", "coactive", "geo", "weblink"):
        out[f"motifs3_{name}"] = build(name, _TRI, select=_MOTIF3)
    for name in ("similar", "copart"):
        out[f"motifs4_{name}"] = build(name, _SETS3, _SETS4, _DEGS4, select=_MOTIF4)
    for name in ("motifs3_filter_only", "motifs3_engine_paths", "motifs3_waves", "two_level_equals_one", "vertex_centric_motifs", "census3"):
        out[name] = out["motifs3_similar"]
    out["census4"] = out["motifs4_similar"]
    out["motifs_upto4_similar"] = build("similar", _TRI, _SETS3, _SETS4, _DEGS4, select=f"{_MOTIF4} UNION ALL ({_MOTIF3})")
    out["motif_top2"] = build("copart", _SETS3, _SETS4, _DEGS4, select=f"{_MOTIF4} ORDER BY n DESC, degs LIMIT 2")
    out["motifs3_labelled_copart"] = build("copart", _SETS3, _ORDER3, select="SELECT CAST(3 AS BIGINT) AS k, CAST(n_edges AS BIGINT) AS n_edges, CASE n_edges WHEN 2 THEN '1-1-2' ELSE '2-2-2' END AS degs, array_to_string(list_sort([a.label, b.label, c.label]), '|') AS lbls, count(*) AS n FROM f3 JOIN lab a ON a.vid = w0 JOIN lab b ON b.vid = w1 JOIN lab c ON c.vid = w2 GROUP BY ALL")
    out["motifs3_by_graph"] = "SELECT conv_id, CAST(2 AS BIGINT) AS n_edges, count(DISTINCT turn) - 2 AS n FROM conversations GROUP BY conv_id HAVING count(DISTINCT turn) > 2"
    out["graph_support_conversations"] = build("conversations", select="SELECT array_to_string(list_sort([la, lc, lb]), '|') AS lbls, max(support) AS support FROM (SELECT least(a.label, b.label) AS la, c.label AS lc, greatest(a.label, b.label) AS lb, count(DISTINCT c.vid // 100000) AS support FROM e p JOIN e q ON p.dst = q.src JOIN lab a ON a.vid = p.src JOIN lab c ON c.vid = p.dst JOIN lab b ON b.vid = q.dst GROUP BY ALL) GROUP BY lbls")
    out["vertex_embeddings3"] = build("similar", _SETS3, _ORDER3, select="SELECT w0 AS v1, w1 AS v2, w2 AS v3 FROM f3")
    out["store_roundtrip"] = out["store_roundtrip_single"] = out["vertex_embeddings3"]
    out["dedupe_global"] = build("similar", _SETS3, select="SELECT x AS v1, y AS v2, z AS v3 FROM s3")
    pairs = "inc AS MATERIALIZED (SELECT DISTINCT a.eid AS f, b.eid AS t FROM adj a JOIN adj b ON a.vid = b.vid AND a.eid <> b.eid)"
    out["edge_embeddings2"] = build("copart", pairs, select="SELECT f AS e1, t AS e2 FROM inc WHERE f < t")
    out["edge_embeddings3_sets"] = build("similar", pairs, select="SELECT DISTINCT q[1] AS s1, q[2] AS s2, q[3] AS s3 FROM (SELECT list_sort([a.f, a.t, b.t]) AS q FROM inc a JOIN inc b ON b.f = a.t WHERE b.t <> a.f)")
    size1 = "SELECT 1 AS step, (SELECT count(*) FROM lab) AS n"
    out["funnel_similar"] = build("similar", _SETS3, select="""SELECT CAST(step AS BIGINT) AS step, candidates, canonical FROM (
SELECT 1 AS step, (SELECT count(*) FROM lab) AS candidates, (SELECT count(*) FROM lab) AS canonical
UNION ALL SELECT 2, (SELECT count(*) FROM e), (SELECT count(*) FROM e)
UNION ALL SELECT 3, (SELECT count(*) FROM (SELECT DISTINCT src, dst, nbr FROM (SELECT src, dst, unnest([src, dst]) AS vid FROM e) JOIN adj USING (vid) WHERE nbr > src AND nbr <> dst)), (SELECT count(*) FROM s3))""")
    out["growth_similar"] = build("similar", _SETS3, _SETS4, select=f"SELECT CAST(step AS BIGINT) AS size, n FROM ({size1} UNION ALL SELECT 2, (SELECT count(*) FROM e) UNION ALL SELECT 3, (SELECT count(*) FROM s3) UNION ALL SELECT 4, (SELECT count(*) FROM s4))")
    out["growth_copart"] = build("copart", _SETS3, select=f"SELECT CAST(step AS BIGINT) AS size, n FROM ({size1} UNION ALL SELECT 2, (SELECT count(*) FROM e) UNION ALL SELECT 3, (SELECT count(*) FROM s3))")
    out["growth_cliques"] = build("docs", *cliques(4), select="SELECT CAST(s AS BIGINT) AS size, n FROM (SELECT 2 AS s, (SELECT count(*) FROM e) AS n UNION ALL SELECT 3, (SELECT count(*) FROM k3) UNION ALL SELECT 4, (SELECT count(*) FROM k4))")
    frequent = f"support >= {THETA}"
    fsm = (_ADJL, _FSM1, _FSM2)
    out["growth_fsm"] = build("copart", *fsm, select=f"SELECT CAST(1 AS BIGINT) AS size, CAST(coalesce(sum(n), 0) AS BIGINT) AS n FROM p1 WHERE {frequent} UNION ALL SELECT 2, CAST(coalesce(sum(n), 0) AS BIGINT) FROM p2 WHERE {frequent}")
    out["cliques3_copart"] = build("copart", *cliques(3), select="SELECT v1, v2, v3 FROM k3")
    out["cliques4_docs"] = out["clique_join4"] = build("docs", *cliques(4), select="SELECT v1, v2, v3, v4 FROM k4")
    out["cliques5_docs"] = build("docs", *cliques(5), select="SELECT v1, v2, v3, v4, v5 FROM k5")
    out["clique_counts_docs"] = build("docs", *cliques(5), select="SELECT CAST(s AS BIGINT) AS k, n FROM (SELECT 1 AS s, (SELECT count(*) FROM deg) AS n UNION ALL SELECT 2, (SELECT count(*) FROM e) UNION ALL SELECT 3, (SELECT count(*) FROM k3) UNION ALL SELECT 4, (SELECT count(*) FROM k4) UNION ALL SELECT 5, (SELECT count(*) FROM k5)) WHERE n > 0")
    out["maximal_cliques_docs"] = _maximal()
    out["frequent_cliques_docs"] = _frequent_cliques()
    out["fsm1_copart"] = build("copart", _ADJL, _FSM1, select=f"SELECT la AS lbl_a, lb AS lbl_b, support FROM p1 WHERE {frequent}")
    out["fsm2_copart"] = out["pattern_centric_copart"] = build("copart", *fsm, select=f"SELECT lc AS center, la AS end_a, lb AS end_b, support FROM p2 WHERE {frequent}")
    out["fsm3_patterns_similar"] = _fsm3()
    out["fsm_embeddings_similar"] = build("similar", *fsm, select="SELECT DISTINCT e1, e2 FROM m2 JOIN p2 USING (lc, la, lb) WHERE support >= 12")
    out["mine_then_match"] = build("copart", *fsm, select=f"SELECT DISTINCT e1, e2 FROM m2 JOIN p2 USING (lc, la, lb) WHERE support >= {THETA}")
    out["fsm_edge_labels"] = build("custsupp", select="""SELECT la AS lbl_a, elabel, lb AS lbl_b, least(count(DISTINCT x), count(DISTINCT y)) AS support FROM (
SELECT a.vid AS x, b.vid AS y, a.label AS la, b.label AS lb, elabel FROM (SELECT src AS s, dst AS t, elabel FROM e UNION ALL SELECT dst, src, elabel FROM e) JOIN lab a ON a.vid = s JOIN lab b ON b.vid = t) WHERE la <= lb GROUP BY la, lb, elabel HAVING least(count(DISTINCT x), count(DISTINCT y)) >= 3""")
    out["fsm_support_sweep"] = build("copart", *fsm, select="SELECT theta, count(support) AS n_frequent, CAST(coalesce(sum(n), 0) AS BIGINT) AS n_kept FROM (SELECT CAST(unnest([60, 90, 120]) AS BIGINT) AS theta) t LEFT JOIN (SELECT support, n FROM p1 UNION ALL SELECT support, n FROM p2) p ON support >= theta GROUP BY theta")
    out["fsm_last_level"] = build("copart", *fsm, select=f"SELECT count(*) AS n_patterns, CAST(coalesce(sum(n), 0) AS BIGINT) AS n_embeddings FROM p2 WHERE {frequent}")
    out["fsm_engine_app"] = build("copart", _ADJL, select="SELECT eid AS e1 FROM (SELECT eid, count(*) OVER (PARTITION BY vl, nl) AS c FROM (SELECT eid, least(vl, nl) AS vl, greatest(vl, nl) AS nl FROM al WHERE vid < nbr)) WHERE c >= 100")
    out["vertex_centric_fsm"] = build("copart", _ADJL, _FSM1, select="SELECT la AS lbl_a, lb AS lbl_b, support FROM p1 WHERE support >= 120")
    out["pattern_centric_early_stop"] = build("copart", _ADJL, _FSM1, select=f"SELECT la AS lbl_a, lb AS lbl_b, least(support, {THETA}) AS support FROM p1 WHERE {frequent}")
    out["match_triangle"] = build("similar", _CLIQ[3], select="SELECT v1, v2, v3 FROM k3")
    square = "a.vid AS v1, a.nbr AS v2, b.nbr AS v3, c.nbr AS v4 FROM adj a JOIN adj b ON b.vid = a.nbr JOIN adj c ON c.vid = b.nbr JOIN adj d ON d.vid = c.nbr AND d.nbr = a.vid WHERE a.vid < a.nbr AND a.vid < b.nbr AND a.vid < c.nbr AND a.nbr < c.nbr"
    out["match_square"] = build("similar", select=f"SELECT {square}")
    out["match_square_induced"] = build("similar", select=f"SELECT * FROM (SELECT {square}) q WHERE NOT EXISTS (SELECT 1 FROM adj WHERE vid = v1 AND nbr = v3) AND NOT EXISTS (SELECT 1 FROM adj WHERE vid = v2 AND nbr = v4)")
    a, b, c = PATH_LABELS
    out["match_labelled_path"] = build("copart", _ADJL, select=f"SELECT p.vid AS v1, p.nbr AS v2, q.nbr AS v3 FROM al p JOIN al q ON q.vid = p.nbr WHERE p.vid < q.nbr AND p.vl = '{a}' AND p.nl = '{b}' AND q.nl = '{c}'")
    out["match_label_cost"] = build("copart", _ADJL, select=f"SELECT p.vid AS v1, p.nbr AS v2, q.nbr AS v3 FROM al p JOIN al q ON q.vid = p.nbr WHERE p.vid <> q.nbr AND CAST(p.vl <> '{a}' AS INT) + CAST(p.nl <> '{b}' AS INT) + CAST(q.nl <> '{c}' AS INT) <= 1")
    out["match_mappings"] = build("similar", select="SELECT a.vid AS v1, a.nbr AS v2, b.nbr AS v3 FROM adj a JOIN adj b ON b.vid = a.nbr JOIN adj c ON c.vid = b.nbr AND c.nbr = a.vid")
    out["dense4"] = build("similar", _SETS3, _SETS4, _DEGS4, select="SELECT q[1] AS v1, q[2] AS v2, q[3] AS v3, q[4] AS v4 FROM d4 WHERE list_sum(l) >= 10")
    out["quick_patterns_similar"] = build("similar", _SETS3, _ORDER3, select="SELECT CAST(3 AS BIGINT) AS k, count(*) AS n_embeddings, count(DISTINCT CASE WHEN n_edges = 3 THEN 3 WHEN xy AND xz THEN 1 ELSE 2 END) AS n_quick, count(DISTINCT n_edges) AS n_canonical FROM f3")
    out["aggregation_reduction"] = ""
    out["store_edges_similar"] = build("similar", _SETS3, _ORDER3, _STORE, select=f"SELECT {longs('n_edges', 'level', 'node', 'next')} FROM st")
    out["store_single"] = out["store_merge"] = build("similar", _SETS3, _ORDER3, _STORE, select=f"SELECT DISTINCT {longs('level', 'node', 'next')} FROM st")
    out["store_sizes"] = build("copart", _SETS3, _ORDER3, _STORE, select="SELECT k, list_words, store_edges, list_words * 8 AS list_bytes, store_edges * 20 AS store_bytes FROM (SELECT CAST(2 AS BIGINT) AS k, 2 * (SELECT count(*) FROM e) AS list_words, (SELECT count(*) FROM e) AS store_edges UNION ALL SELECT 3, 3 * (SELECT count(*) FROM f3), (SELECT count(*) FROM st))")
    out["store_prefix_tree"] = build("similar", _SETS3, _ORDER3, select="SELECT CAST(l AS BIGINT) AS level, n AS n_prefixes FROM (SELECT 0 AS l, (SELECT count(DISTINCT w0) FROM f3) AS n UNION ALL SELECT 1, (SELECT count(DISTINCT (w0, w1)) FROM f3) UNION ALL SELECT 2, (SELECT count(*) FROM f3))")
    out["path_cost"] = build("similar", _SETS3, _ORDER3, _STORE, "one AS (SELECT DISTINCT level, node, next FROM st)", select="SELECT a.node, count(*) AS cost FROM one a JOIN one b ON b.level = 1 AND b.node = a.next WHERE a.level = 0 GROUP BY a.node")
    out["round_robin_blocks"] = build("similar", _SETS3, _ORDER3, select="SELECT CAST((r // 100) % 4 AS BIGINT) AS part, count(*) AS n FROM (SELECT row_number() OVER (ORDER BY w0, w1, w2) - 1 AS r FROM f3) GROUP BY ALL")
    out["round_robin_single"] = build("similar", _SETS3, _ORDER3, select="SELECT CAST(r % 4 AS BIGINT) AS part, count(*) AS n FROM (SELECT row_number() OVER (ORDER BY w0, w1, w2) - 1 AS r FROM f3) GROUP BY ALL")
    out["aggregate_integer_key"] = build("similar", _SETS3, select="SELECT key, count(*) AS n FROM (SELECT vid % 10 AS key FROM lab UNION ALL SELECT src % 10 FROM e UNION ALL SELECT x % 10 FROM s3) GROUP BY key")
    out["output_when_step"] = build("similar", _TRI, select=f"SELECT CAST(step AS BIGINT) AS step, CAST(n_edges AS BIGINT) AS n_edges, CAST(n AS BIGINT) AS n FROM (SELECT 1 AS step, 0 AS n_edges, (SELECT count(*) FROM lab) AS n UNION ALL SELECT 2, 1, (SELECT count(*) FROM e) UNION ALL SELECT 3, n_edges, n FROM ({_MOTIF3}))")
    out["estimate_level3"] = build("similar", select="SELECT CAST(sum(a.d + b.d) AS BIGINT) AS candidates_at_most FROM e JOIN deg a ON a.vid = src JOIN deg b ON b.vid = dst")
    out["vertex_centric_messages"] = build("similar", select="SELECT CAST(step AS BIGINT) AS step, CAST(messages AS BIGINT) AS messages FROM (SELECT 1 AS step, (SELECT count(*) FROM deg) AS messages UNION ALL SELECT 2, (SELECT sum(CAST(a.d > 1 AS INT) + CAST(b.d > 1 AS INT)) FROM e JOIN deg a ON a.vid = src JOIN deg b ON b.vid = dst))")
    out["pattern_centric_skew"] = build("copart", _ADJL, select="SELECT least(vl, nl) || '|' || greatest(vl, nl) AS lbls, count(*) AS n_embeddings FROM al WHERE vid < nbr GROUP BY ALL")
    out["toy_quick"] = build("copart", select="SELECT a.label || '-' || b.label AS quick, least(a.label, b.label) || '-' || greatest(a.label, b.label) AS canonical, count(*) AS n FROM e JOIN lab a ON a.vid = src JOIN lab b ON b.vid = dst GROUP BY ALL")
    out["toy_paths"] = build("conversations", _SETS3, _ORDER3, select="SELECT w0 AS v1, w1 AS v2, w2 AS v3 FROM f3")
    out["toy_spurious"] = "SELECT CAST(6 AS BIGINT) AS n"
    out["toy_redundant"] = build("conversations", pairs, select="SELECT f AS e1, t AS e2 FROM inc WHERE f < t")
    out["degree_hist"] = build("similar", select="SELECT d AS vid, count(*) AS value FROM deg GROUP BY d")
    per_vertex = "tv AS MATERIALIZED (SELECT vid, count(v) AS t FROM deg LEFT JOIN (SELECT unnest([x, y, z]) AS v FROM tri) ON v = vid GROUP BY vid)"
    out["triangles_per_vertex"] = build("similar", _TRI, per_vertex, select="SELECT vid, t AS value FROM tv")
    out["clustering"] = build("similar", _TRI, per_vertex, select="SELECT vid, round(CASE WHEN d > 1 THEN CAST(2 * t AS DOUBLE) / (d * (d - 1)) ELSE 0 END, 6) AS value FROM tv JOIN deg USING (vid)")
    out["components"] = graph("similar").replace("WITH", "WITH RECURSIVE", 1) + ", r AS (SELECT vid, vid AS c FROM deg UNION SELECT adj.nbr, r.c FROM r JOIN adj ON adj.vid = r.vid WHERE r.c < adj.nbr)\nSELECT vid, min(c) AS value FROM r GROUP BY vid"
    peel, last = [], "adj"
    for i in range(30):  # more rounds than the graph has tails; a fixpoint stays
        peel.append(f"c{i} AS MATERIALIZED (SELECT vid, nbr FROM {last} WHERE vid IN (SELECT vid FROM {last} GROUP BY vid HAVING count(*) >= 2) AND nbr IN (SELECT vid FROM {last} GROUP BY vid HAVING count(*) >= 2))")
        last = f"c{i}"
    out["kcore2"] = build("similar", *peel, select=f"SELECT vid, count(*) AS value FROM {last} GROUP BY vid")
    out["aggregation_reduction"] = build("similar", _SETS3, _SETS4, _DEGS4, _ORDER4, select=_REDUCTION)
    # One pattern's paths have the ordinals 0 to t - 1; part p of 4 has those x with floor(4 x / t) = p.
    paths = "tot AS (SELECT a.n_edges, count(*) AS t FROM st a JOIN st b ON a.level = 0 AND b.level = 1 AND a.n_edges = b.n_edges AND a.next = b.node GROUP BY a.n_edges), part AS (SELECT p, sum((t * (p + 1) + 3) // 4 - (t * p + 3) // 4) AS cost FROM tot, (SELECT unnest([0, 1, 2, 3]) AS p) GROUP BY p HAVING sum((t * (p + 1) + 3) // 4 - (t * p + 3) // 4) > 0)"
    out["path_partition"] = build("similar", _SETS3, _ORDER3, _STORE, paths, select="SELECT CAST(p AS BIGINT) AS part, CAST(cost AS BIGINT) AS cost FROM part")
    out["path_balance"] = build("similar", _SETS3, _ORDER3, _STORE, paths, select="SELECT count(*) AS n_parts, CAST(max(cost) AS DOUBLE) AS most, avg(CAST(cost AS DOUBLE)) AS mean, round(max(cost) / avg(CAST(cost AS DOUBLE)), 6) AS imbalance FROM part")
    out["support_approx"] = out["fsm1_copart"]
    for name in ("embedding", "vertex", "pattern"):
        out[f"paradigm_fsm_{name}"] = out["fsm2_copart"]
    out["paradigm_messages"] = build("copart", _ADJL, _FSM1, select=f"""SELECT paradigm, CAST(messages AS BIGINT) AS messages FROM (
SELECT 'embedding' AS paradigm, (SELECT coalesce(sum(n), 0) FROM p1 WHERE {frequent}) AS messages
UNION ALL SELECT 'vertex', (SELECT coalesce(sum(CAST(a.d > 1 AS INT) + CAST(b.d > 1 AS INT)), 0) FROM al JOIN deg a ON a.vid = al.vid JOIN deg b ON b.vid = al.nbr JOIN p1 ON la = least(vl, nl) AND lb = greatest(vl, nl) WHERE al.vid < al.nbr AND {frequent})
UNION ALL SELECT 'pattern', 0)""")
    out["fsm_engine_paths"] = out["mine_then_match"]
    out["fsm3_copart"] = out["fsm3_copart_paths"] = _fsm3("copart", DEEP)
    out["fsm_no_maximum"] = _fsm3("copart", NO_MAXIMUM)
    out["fsm2_custsupp"] = build("custsupp", """al AS MATERIALIZED (SELECT adj.*, a.label AS vl, b.label || ':' || e.elabel AS arm FROM adj JOIN e USING (eid) JOIN lab a ON a.vid = adj.vid JOIN lab b ON b.vid = adj.nbr)""", select="SELECT a.vl AS center, a.arm AS arm_a, b.arm AS arm_b, least(count(DISTINCT a.vid), count(DISTINCT a.nbr), count(DISTINCT b.nbr)) AS support FROM al a JOIN al b ON a.vid = b.vid AND a.nbr <> b.nbr WHERE a.arm <= b.arm GROUP BY ALL HAVING least(count(DISTINCT a.vid), count(DISTINCT a.nbr), count(DISTINCT b.nbr)) >= 2")
    triples = "t3 AS (SELECT DISTINCT q FROM (SELECT list_sort([a.f, a.t, b.t]) AS q FROM inc a JOIN inc b ON b.f = a.t WHERE b.t <> a.f))"
    out["store_size_fsm"] = build("copart", pairs, triples, select="SELECT k, list_words, list_words * 8 AS list_bytes FROM (SELECT CAST(2 AS BIGINT) AS k, (SELECT count(*) FROM inc) AS list_words UNION ALL SELECT 3, 3 * (SELECT count(*) FROM t3))")
    out["store_size_coactive"] = build("coactive", _SETS3, _ORDER3, _STORE, select="SELECT CAST(3 AS BIGINT) AS k, list_words, store_edges, list_words * 8 AS list_bytes, store_edges * 20 AS store_bytes FROM (SELECT 3 * (SELECT count(*) FROM f3) AS list_words, (SELECT count(*) FROM st) AS store_edges)")
    one = "one AS (SELECT DISTINCT level, node, next FROM st)"
    out["store_spurious"] = build("similar", _SETS3, _ORDER3, _STORE, one, select="SELECT store_edges, paths, embeddings, paths - embeddings AS spurious FROM (SELECT (SELECT count(*) FROM one) AS store_edges, (SELECT count(*) FROM one a JOIN one b ON a.level = 0 AND b.level = 1 AND b.node = a.next) AS paths, (SELECT count(*) FROM f3) AS embeddings)")
    out["store_roundtrip_edges"] = out["edge_embeddings2"]
    out["store_roundtrip_parts"] = out["vertex_embeddings3"]
    out["store_roundtrip_labelled"] = out["motifs3_engine_labelled_paths"] = out["motifs3_labelled_copart"]
    for name in ("custsupp", "coactive"):
        out[f"two_level_{name}"] = build(name, _SETS3, _ORDER3, select=out["quick_patterns_similar"].rsplit("\n", 1)[1])
    out["two_level_fsm"] = build("copart", _ADJL, select="""SELECT count(*) AS n_embeddings, count(DISTINCT (shared, l1, l2, l3)) AS n_quick, count(DISTINCT (CASE shared WHEN 1 THEN l1 ELSE l2 END, least(l3, CASE shared WHEN 1 THEN l2 ELSE l1 END), greatest(l3, CASE shared WHEN 1 THEN l2 ELSE l1 END))) AS n_canonical FROM (
SELECT CASE WHEN x.src IN (y.src, y.dst) THEN 1 ELSE 2 END AS shared, a.label AS l1, b.label AS l2, c.label AS l3
FROM e x JOIN e y ON x.eid < y.eid AND (x.src IN (y.src, y.dst) OR x.dst IN (y.src, y.dst)) JOIN lab a ON a.vid = x.src JOIN lab b ON b.vid = x.dst JOIN lab c ON c.vid = CASE WHEN y.src IN (x.src, x.dst) THEN y.dst ELSE y.src END)""")
    out["one_level_custsupp"] = out["motifs3_custsupp"]
    out["motifs_upto4_copart"] = build("copart", _TRI, _SETS3, _SETS4, _DEGS4, select=f"{_MOTIF4} UNION ALL ({_MOTIF3})")
    out["outputs_to_sink"] = build("docs", _CLIQ[3], select="SELECT CAST(s AS BIGINT) AS k, n FROM (SELECT 2 AS s, (SELECT count(*) FROM e) AS n UNION ALL SELECT 3, (SELECT count(*) FROM k3)) WHERE n > 0")
    out["degree_filter"] = build("similar", select="""SELECT CAST(size AS BIGINT) AS size, n FROM (
SELECT 1 AS size, (SELECT count(*) FROM low) AS n UNION ALL SELECT 2, (SELECT count(*) FROM link WHERE vid < nbr)
UNION ALL SELECT 3, (SELECT count(DISTINCT list_sort([p.vid, p.nbr, r.nbr])) FROM link p JOIN link r ON p.nbr = r.vid WHERE p.vid <> r.nbr)) WHERE n > 0""").replace("lab AS MATERIALIZED", "low AS MATERIALIZED (SELECT vid FROM deg WHERE d <= 8), link AS MATERIALIZED (SELECT vid, nbr FROM adj WHERE vid IN (SELECT vid FROM low) AND nbr IN (SELECT vid FROM low)),\nlab AS MATERIALIZED")
    out["census4_tree"] = out["motifs4_similar"]
    out["census5_copart"] = out["motifs5_copart"] = build("copart", _SETS3, _SETS4, _SETS5, select="SELECT CAST(5 AS BIGINT) AS k, CAST(list_sum(l) / 2 AS BIGINT) AS n_edges, array_to_string(l, '-') AS degs, count(*) AS n FROM d5 GROUP BY ALL")
    ranks, last = [], "(SELECT vid, 1.0 / (SELECT count(*) FROM deg) AS r FROM deg)"
    for i in range(4):
        ranks.append(f"pr{i} AS MATERIALIZED (SELECT adj.nbr AS vid, 0.15 / (SELECT count(*) FROM deg) + 0.85 * sum(r / d) AS r FROM {last} z JOIN deg USING (vid) JOIN adj USING (vid) GROUP BY adj.nbr)")
        last = f"pr{i}"
    out["page_rank"] = build("similar", *ranks, select="SELECT vid, round(CAST(r AS DOUBLE), 8) AS value FROM pr3")
    held = "fr AS (SELECT * FROM p1 WHERE support >= 120)"
    out["pattern_centric_workers"] = build("copart", *fsm, held, select="SELECT CAST(1 AS BIGINT) AS size, la || '|' || lb AS lbls, (SELECT count(*) FROM al WHERE vl = la AND nl = lb) AS n_mappings FROM fr UNION ALL SELECT 2, array_to_string(list_sort([lc, la, lb]), '|'), count(*) FROM m2 JOIN p2 USING (lc, la, lb) WHERE support >= 120 GROUP BY lc, la, lb")
    out["pattern_centric_skew"] = build("copart", *fsm, held, select="SELECT count(*) AS n, max(c) AS most, round(avg(c), 6) AS mean, round(CAST(max(c) AS DOUBLE) / sum(c), 6) AS share FROM (SELECT (SELECT count(*) FROM al WHERE vl = la AND nl = lb) AS c FROM fr)")
    return out


_SETS5 = """s5 AS MATERIALIZED (SELECT DISTINCT list_sort(list_append(q, nbr)) AS q FROM (SELECT q, unnest(q) AS vid FROM s4) JOIN adj USING (vid) WHERE NOT list_contains(q, nbr)),
d5 AS MATERIALIZED (SELECT q, list_sort(list(c)) AS l FROM (SELECT q, v, count(*) AS c FROM (SELECT q, unnest(q) AS v FROM s5) JOIN adj ON adj.vid = v WHERE list_contains(q, nbr) GROUP BY q, v) GROUP BY q)"""
# Visiting order of a connected 4-set, step by step: the smallest word, then the smallest unvisited neighbour.
_ORDER4 = """o1 AS (SELECT q, l, q[1] AS w0 FROM d4),
o2 AS (SELECT q, any_value(l) AS l, w0, min(nbr) AS w1 FROM o1 JOIN adj ON vid = w0 WHERE list_contains(q, nbr) GROUP BY q, w0),
o3 AS (SELECT q, any_value(l) AS l, w0, w1, min(nbr) AS w2 FROM o2 JOIN adj ON vid IN (w0, w1) WHERE list_contains(q, nbr) AND nbr NOT IN (w0, w1) GROUP BY q, w0, w1),
o4 AS MATERIALIZED (SELECT q, l, w0, w1, w2, list_filter(q, lambda x: x NOT IN (w0, w1, w2))[1] AS w3 FROM o3),
c4 AS MATERIALIZED (SELECT l, q, list_sort(list(CASE WHEN (a, b) IN ((w0, w2), (w2, w0)) THEN 1 WHEN (a, b) IN ((w1, w2), (w2, w1)) THEN 2 WHEN (a, b) IN ((w0, w3), (w3, w0)) THEN 3 WHEN (a, b) IN ((w1, w3), (w3, w1)) THEN 4 WHEN (a, b) IN ((w2, w3), (w3, w2)) THEN 5 ELSE 0 END)) AS code
FROM (SELECT o4.*, unnest(q) AS a FROM o4) JOIN (SELECT vid, nbr AS b FROM adj) ON vid = a WHERE a < b AND list_contains(q, b) GROUP BY l, q)"""
_REDUCTION = "SELECT CAST(4 AS BIGINT) AS k, count(*) AS n_embeddings, count(DISTINCT code) AS n_quick, count(DISTINCT l) AS n_canonical, round(CAST(count(*) AS DOUBLE) / count(DISTINCT code), 6) AS reduction FROM c4"
