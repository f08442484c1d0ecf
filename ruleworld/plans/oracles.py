"""SQL that restates the library's queries over the given tables, for an independent engine."""

from __future__ import annotations

from ruleworld.functions.similarity import COSINE_SQL, JACCARD_SQL
from ruleworld.plans.workloads import EVENT_TYPES, band_weight

# Clause tables ``cl(rule, lits, weight, is_hard)``, one row an undecided instance, and atoms.

RC_ATOMS = """
classes AS (SELECT unnest([0, 1]) AS cls),
known AS (SELECT doc_id, max(quality) AS q FROM labels GROUP BY doc_id),
topic AS (SELECT row_number() OVER (ORDER BY doc_id, cls) AS aid, doc_id, cls,
                 CASE WHEN q IS NULL THEN -1 WHEN q = cls THEN 1 ELSE 0 END AS truth
          FROM (SELECT DISTINCT doc_id FROM documents) CROSS JOIN classes LEFT JOIN known USING (doc_id)),
cites AS (SELECT DISTINCT d1, d2 FROM (
            SELECT doc_id AS d1, lead(doc_id) OVER (PARTITION BY source, lang ORDER BY doc_id) AS d2 FROM documents
            UNION ALL SELECT doc_id, lead(doc_id) OVER (PARTITION BY text ORDER BY doc_id) FROM documents)
          WHERE d2 IS NOT NULL)"""


def pair(x: str, y: str, sx: str, sy: str) -> str:
    """Two signed literals, those of unknown atoms only, in the order of their atoms."""
    a, b = f"CASE WHEN {x}.truth = -1 THEN {sx}{x}.aid END", f"CASE WHEN {y}.truth = -1 THEN {sy}{y}.aid END"
    return f"list_filter(CASE WHEN {x}.aid < {y}.aid THEN [{a}, {b}] ELSE [{b}, {a}] END, lambda v: v IS NOT NULL)"


RC_KEY = f"SELECT 'r1' AS rule, {pair('x', 'y', '-', '-')} AS lits, 5.0 AS weight FROM topic x JOIN topic y ON x.doc_id = y.doc_id AND x.cls <> y.cls WHERE x.truth <> 0 AND y.truth <> 0"
RC_CITE = f"SELECT 'r2' AS rule, {pair('x', 'y', '-', '')} AS lits, 1.0 AS weight FROM topic x JOIN cites ON d1 = x.doc_id JOIN topic y ON d2 = y.doc_id AND x.cls = y.cls WHERE x.truth <> 0 AND y.truth <> 1"
RC_BACK = f"SELECT 'r3' AS rule, {pair('x', 'y', '-', '')} AS lits, 1.0 AS weight FROM topic x JOIN cites ON d2 = x.doc_id JOIN topic y ON d1 = y.doc_id AND x.cls = y.cls WHERE x.truth <> 0 AND y.truth <> 1"
RC_PRIOR = "SELECT 'r4' AS rule, [aid] AS lits, -1.0 AS weight FROM topic WHERE cls = 0 AND truth = -1"
RC_AUTHOR = f"SELECT 'r5' AS rule, {pair('x', 'y', '-', '')} AS lits, 1.0 AS weight FROM authored u JOIN authored v USING (source) JOIN topic x ON x.doc_id = u.doc_id JOIN topic y ON y.doc_id = v.doc_id AND x.cls = y.cls WHERE x.truth <> 0 AND y.truth <> 1 AND x.aid <> y.aid"
RC_RAW = f"raw AS ({RC_KEY} UNION ALL {RC_CITE} UNION ALL {RC_BACK} UNION ALL {RC_PRIOR})"
MERGE = """
cl AS (SELECT row_number() OVER (ORDER BY rule, lits) AS cid, rule, lits, sum(weight) AS weight, count(*) AS multiplicity
       FROM raw WHERE len(lits) > 0 GROUP BY rule, lits)"""
RC = f"WITH RECURSIVE {RC_ATOMS}, {RC_RAW}, {MERGE}"

_SEQ = """
seen AS (SELECT row_number() OVER (ORDER BY event_id) AS aid, event_id, user_id, ts, event_type,
                CAST(least(floor(value / 50), 9) AS INT) AS band FROM events),
near AS (SELECT aid AS e, a2 AS f FROM (
           SELECT aid, ts, lead(aid) OVER w AS a2, lead(ts) OVER w AS ts2 FROM seen WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id))
         WHERE ts2 <= ts + INTERVAL 60 MINUTES)"""
_BANDS = ", ".join(f"('{kind}', {b}, {band_weight(k, b)}, 'r{10 * k + b + 1}')" for k, kind in enumerate(EVENT_TYPES) for b in range(10))
_TWO = "CASE WHEN {0} < {1} THEN [{2}{0}, {3}{1}] ELSE [{3}{1}, {2}{0}] END"
IE_PAIRS = f"SELECT 'r51' AS rule, {_TWO.format('e', 'f', '-', '')} AS lits, 2.0 AS weight FROM near UNION ALL SELECT 'r52', {_TWO.format('f', 'e', '-', '')}, 1.5 FROM near"
IE_RAW = f"bands(event_type, band, w, rule) AS (VALUES {_BANDS}), raw AS (SELECT rule, [CASE WHEN w > 0 THEN aid ELSE -aid END] AS lits, CAST(abs(w) AS DOUBLE) AS weight FROM seen JOIN bands USING (event_type, band) UNION ALL {IE_PAIRS})"
IE = f"WITH RECURSIVE {_SEQ}, {IE_RAW}, {MERGE}"

EX1 = f"""WITH RECURSIVE k AS (SELECT n_nationkey AS k, row_number() OVER (ORDER BY n_nationkey) AS i, count(*) OVER () AS n FROM nation),
raw AS (SELECT 'r1' AS rule, [i] AS lits, 1.0 AS weight FROM k UNION ALL SELECT 'r2', [n + i], 1.0 FROM k UNION ALL SELECT 'r3', [i, n + i], -1.0 FROM k), {MERGE}"""

EX2 = f"""WITH RECURSIVE nodes AS (SELECT n_nationkey AS k, n_regionkey AS r, row_number() OVER (ORDER BY n_nationkey) AS aid FROM nation WHERE n_regionkey IN (0, 1)),
ring AS (SELECT aid AS x, coalesce(lead(aid) OVER (PARTITION BY r ORDER BY k), min(aid) OVER (PARTITION BY r)) AS y, k FROM nodes),
ends AS (SELECT min(aid) FILTER (r = 0) AS x, min(aid) FILTER (r = 1) AS y FROM nodes),
raw AS (SELECT 'r1' AS rule, {_TWO.format('x', 'y', '-', '')} AS lits, 2.0 AS weight FROM ring
        UNION ALL SELECT 'r2', {_TWO.format('x', 'y', '-', '-')}, 1.0 FROM ends
        UNION ALL SELECT 'r3', [aid], 0.75 FROM nodes WHERE k % 2 = 1
        UNION ALL SELECT 'r4', [-aid], 1.25 FROM nodes WHERE k % 3 = 0
        UNION ALL SELECT 'r5', {_TWO.format('x', 'y', '-', '-')}, 0.5 FROM ring WHERE k % 2 = 1), {MERGE}"""

LP = f"""WITH RECURSIVE t AS (SELECT row_number() OVER (ORDER BY c, s) AS aid, c, s, n FROM (
    SELECT o_custkey AS c, l_suppkey AS s, least(count(DISTINCT o_orderkey), 3) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL HAVING count(DISTINCT o_orderkey) >= 2)),
alike AS (SELECT x, y FROM (SELECT c_custkey AS x, lead(c_custkey) OVER (PARTITION BY c_nationkey, c_mktsegment ORDER BY c_custkey) AS y FROM customer) WHERE y IS NOT NULL),
raw AS (SELECT 'r1' AS rule, {_TWO.format('x.aid', 'y.aid', '-', '-')} AS lits, 3.0 AS weight FROM t x JOIN t y ON x.c = y.c AND x.s <> y.s
        UNION ALL SELECT 'r2', [aid], 1.0 FROM t WHERE n = 3
        UNION ALL SELECT 'r3', [aid], 0.5 FROM t WHERE n = 2
        UNION ALL SELECT 'r4', [aid], 1.0 FROM t JOIN customer ON c = c_custkey JOIN supplier ON s = s_suppkey WHERE c_nationkey = s_nationkey
        UNION ALL SELECT 'r5', {_TWO.format('x.aid', 'y.aid', '-', '')}, 0.5 FROM t x JOIN alike ON alike.x = x.c JOIN t y ON y.c = alike.y AND y.s = x.s), {MERGE}"""

_THREE = "list_transform(list_sort([x.aid * 2, y.aid * 2, z.aid * 2 + 1]), lambda v: CASE WHEN v % 2 = 1 THEN v // 2 ELSE -(v // 2) END)"
ER2 = f"""WITH RECURSIVE {JACCARD_SQL}, two AS (SELECT d1 AS p, d2 AS q, sim FROM jac WHERE sim >= 0.5 UNION ALL SELECT d2, d1, sim FROM jac WHERE sim >= 0.5),
t2 AS (SELECT row_number() OVER (ORDER BY p, q) AS aid, p, q, sim FROM two),
raw AS (SELECT 'r1' AS rule, [aid] AS lits, 2.0 AS weight FROM t2 WHERE sim >= 0.8
        UNION ALL SELECT 'r2', [aid], 0.5 FROM t2 JOIN documents a ON a.doc_id = p JOIN documents b ON b.doc_id = q WHERE a.lang = b.lang
        UNION ALL SELECT 'r3', [aid], -1.0 FROM t2
        UNION ALL SELECT 'r4', {_TWO.format('x.aid', 'y.aid', '-', '')}, 1.0 FROM t2 x JOIN t2 y ON y.p = x.q AND y.q = x.p
        UNION ALL SELECT 'r5', {_THREE}, 3.0 FROM t2 x JOIN t2 y ON x.q = y.p JOIN t2 z ON z.p = x.p AND z.q = y.q),
cl AS (SELECT rule, lits, CASE WHEN rule = 'r4' THEN 1.0 ELSE sum(weight) END AS weight, count(*) AS multiplicity FROM raw GROUP BY rule, lits)"""

ER3 = f"""WITH {COSINE_SQL}, pairs AS (SELECT * FROM cos WHERE sim >= 0.3),
two AS (SELECT DISTINCT * FROM (SELECT v1 AS p, v2 AS q, sim FROM pairs UNION ALL SELECT v2, v1, sim FROM pairs)),
t AS (SELECT row_number() OVER (ORDER BY p, q) AS aid, p, q, sim FROM two),
raw AS (SELECT 'r1' AS rule, [aid] AS lits, 2.0 AS weight FROM t WHERE sim >= 0.4
        UNION ALL SELECT 'r2', [aid], 1.0 FROM t JOIN embeddings a ON a.vec_id = p JOIN embeddings b ON b.vec_id = q WHERE a.label = b.label
        UNION ALL SELECT 'r3', [aid], -1.0 FROM t)"""

# Parts that follow a clause table.

COMPONENTS = """
lit AS (SELECT cid, abs(x) AS aid, x > 0 AS pos FROM (SELECT cid, unnest(lits) AS x FROM cl)),
edge AS (SELECT DISTINCT abs(lits[1]) AS a, abs(lits[2]) AS b FROM cl WHERE len(lits) = 2),
both_ways AS (SELECT a, b FROM edge UNION SELECT b, a FROM edge),
reach AS (SELECT DISTINCT aid AS a, aid AS r FROM lit UNION SELECT e.b, reach.r FROM reach JOIN both_ways e ON e.a = reach.a WHERE reach.r < e.b),
comps AS (SELECT a AS aid, min(r) AS comp FROM reach GROUP BY a)"""

ENUMERATED = f"""{COMPONENTS},
ranked AS (SELECT aid, comp, row_number() OVER (PARTITION BY comp ORDER BY aid) - 1 AS k, count(*) OVER (PARTITION BY comp) AS n FROM comps),
sized AS (SELECT DISTINCT comp, n FROM ranked WHERE n <= {{most}}),
worlds AS (SELECT comp, n, unnest(generate_series(0, CAST(2 ** n AS BIGINT) - 1)) AS w FROM sized),
told AS (SELECT ranked.comp, worlds.w, lit.cid, bool_or(((worlds.w >> k) & 1 = 1) = pos) AS yes
         FROM lit JOIN ranked USING (aid) JOIN worlds ON worlds.comp = ranked.comp GROUP BY ALL),
costs AS (SELECT comp, w, sum(CASE WHEN yes <> (weight > 0) THEN abs(weight) ELSE 0 END) AS cost FROM told JOIN cl USING (cid) GROUP BY ALL)"""


def enumerated(most: int) -> str:
    return ENUMERATED.format(most=most)


BEST = "SELECT comp, atoms, CAST(0 AS BIGINT) AS hard, soft, count(*) AS optima FROM (SELECT comp, w, cost, min(cost) OVER (PARTITION BY comp) AS soft FROM costs) JOIN (SELECT comp, n AS atoms FROM sized) USING (comp) WHERE cost <= soft + 1e-9 GROUP BY comp, atoms, soft"
LITS = "array_to_string(lits, ',') AS lits"


def world_cost(value: str) -> str:
    """Cost by rule of the world where every atom is ``value``."""
    true = "list_count(list_filter(lits, lambda x: x > 0)) > 0" if value == "true" else "list_count(list_filter(lits, lambda x: x < 0)) > 0"
    return f"bad AS (SELECT cid, rule, lits, weight FROM cl WHERE ({true}) <> (weight > 0))"
