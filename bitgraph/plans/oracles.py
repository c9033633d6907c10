"""DuckDB SQL over the raw tables, from which the oracles are composed."""

from __future__ import annotations

from bitgraph.sources.graphs import triples_sql


def with_graph(name: str, body: str, ids: bool = False, anchors: bool = False) -> str:
    """``body`` after CTEs: g (s, p, o), with ``ids`` terms, preds, n and ids, with ``anchors`` k of 10 rows of constants."""
    parts = [f"g AS MATERIALIZED ({triples_sql(name)})"]
    if ids:
        parts += [
            "roles AS (SELECT term, CASE bit_or(f) WHEN 3 THEN 'SO' WHEN 1 THEN 'S' ELSE 'O' END AS role FROM (SELECT s AS term, 1 AS f FROM g UNION ALL SELECT o, 2 FROM g) u GROUP BY term)",
            "n AS (SELECT count(*) FILTER (role = 'SO') AS n_so, count(*) FILTER (role = 'S') AS n_s, count(*) FILTER (role = 'O') AS n_o FROM roles)",
            "ranked AS (SELECT term, role, row_number() OVER (PARTITION BY role ORDER BY term) + CASE role WHEN 'SO' THEN 0 ELSE (SELECT n_so FROM n) END AS id FROM roles)",
            "terms AS (SELECT term, role, CAST(CASE WHEN role <> 'O' THEN id END AS BIGINT) AS s_id, CAST(CASE WHEN role <> 'S' THEN id END AS BIGINT) AS o_id FROM ranked)",
            "preds AS (SELECT p AS pred, CAST(row_number() OVER (ORDER BY p) AS BIGINT) AS p_id, count(*) AS n_triples, count(DISTINCT s) AS n_subj, count(DISTINCT o) AS n_obj FROM g GROUP BY p)",
            "ids AS MATERIALIZED (SELECT a.s_id, q.p_id, b.o_id FROM g JOIN terms a ON a.term = g.s AND a.s_id IS NOT NULL JOIN terms b ON b.term = g.o AND b.o_id IS NOT NULL JOIN preds q ON q.pred = g.p)",
            "dim AS (SELECT greatest(1, n_so + greatest(n_s, n_o)) AS d FROM n)",
        ]
    if anchors:
        parts += [DATED_ANCHORS if name == "daily" else ANCHORS]
    return f"WITH {', '.join(parts)} {body}"


#: Ten constants of each kind, such that every join template has an answer.
ANCHORS = """k0 AS (SELECT s AS o1, o AS p1, md5(concat_ws('|', s, p, o)) AS h FROM g WHERE p = 'containsPart' ORDER BY h LIMIT 10),
k AS (SELECT CAST(row_number() OVER (ORDER BY h) AS BIGINT) AS i, o1, p1,
 (SELECT min(b.o) FROM g b JOIN g c ON c.p = 'soldBy' AND c.o = b.o AND c.s = k0.p1 WHERE b.p = 'shippedBy' AND b.s = k0.o1) AS s1,
 (SELECT min(b.o) FROM g b JOIN g c ON c.p = 'inNation' AND c.s = b.o WHERE b.p = 'placedBy' AND b.s = k0.o1) AS c1,
 (SELECT min(c.o) FROM g b JOIN g c ON c.p = 'inNation' AND c.s = b.o WHERE b.p = 'placedBy' AND b.s = k0.o1) AS n1,
 (SELECT min(b.s) FROM g b WHERE b.p = 'containsPart' AND b.o = k0.p1 AND b.s <> k0.o1) AS o2 FROM k0)"""


#: Ten facts of the daily graph with what lies beside them.
DATED_ANCHORS = """k0 AS (SELECT CAST(row_number() OVER (ORDER BY md5(concat_ws('|', s, p, o))) AS BIGINT) AS i, s AS o1, p AS d1, o AS p1 FROM g WHERE p LIKE 'shippedOn/%' ORDER BY i LIMIT 10),
sold AS (SELECT i, min(row(p, o)) AS m FROM k0 JOIN g ON s = p1 WHERE p LIKE 'soldOn/%' GROUP BY i),
beside AS (SELECT i, min(row(p, o)) AS m FROM k0 JOIN g ON s = o1 WHERE o <> p1 GROUP BY i),
other AS (SELECT i, min(row(p, s)) AS m FROM k0 JOIN g ON o = p1 WHERE s <> o1 GROUP BY i),
k AS (SELECT i, o1, d1, p1, sold.m[1] AS d2, sold.m[2] AS s1, beside.m[1] AS d3, beside.m[2] AS p3, other.m[1] AS d4, other.m[2] AS o2 FROM k0 LEFT JOIN sold USING (i) LEFT JOIN beside USING (i) LEFT JOIN other USING (i))"""


def drawn(n: int) -> str:
    """The n facts with the smallest hash: a term comes up as often as it is used."""
    return f"SELECT s, p, o FROM g ORDER BY md5(concat_ws('|', s, p, o)) LIMIT {n}"


#: Levels of a schedule on the graph's side, as (level, cum, below, k): digits so far and left.
LEVELS = {
    "k2": "SELECT level, h - 1 - level AS below, 2 AS k FROM (SELECT unnest(range(h)) AS level, h FROM (SELECT greatest(1, CAST(ceil(log2(d)) AS INT)) AS h FROM dim) a) b",
    "k4": "SELECT level, 2 * (h - 1 - level) AS below, 4 AS k FROM (SELECT unnest(range(h)) AS level, h FROM (SELECT greatest(1, CAST(ceil(log2(d) / 2) AS INT)) AS h FROM dim) a) b",
    "hybrid": """SELECT level, CASE WHEN level < 5 THEN least(2 * h, 10) - 2 * level - 2 + greatest(h - 5, 0) ELSE h - 1 - level END AS below, CASE WHEN level < 5 THEN 4 ELSE 2 END AS k
 FROM (SELECT unnest(range(h)) AS level, h FROM (SELECT CASE WHEN d <= 1024 THEN greatest(1, CAST(ceil(log2(d) / 2) AS INT)) ELSE 5 + CAST(ceil(log2(d / 1024.0)) AS INT) END AS h FROM dim) a) b""",
}


def level_profile(schedule: str) -> str:
    """CTE body of (level, k, ones): nodes that are not empty."""
    return f"SELECT l.level, l.k, count(DISTINCT (p_id, (s_id - 1) >> CAST(l.below AS INT), (o_id - 1) >> CAST(l.below AS INT))) AS ones FROM ids, ({LEVELS[schedule]}) l GROUP BY l.level, l.k"


def level_bits(schedule: str) -> str:
    return f"SELECT level, ones, CAST(k * k * coalesce(lag(ones) OVER (ORDER BY level), (SELECT count(*) FROM preds)) AS BIGINT) AS n_bits FROM ({level_profile(schedule)}) y"
