"""DuckDB SQL for the registered queries, written on names and plain reachability.

Nothing of the Spark path is used: vertices are strings, the two levels are two recursive
reachabilities, and the as-of join is DuckDB's own.
"""

from __future__ import annotations

# Seeds as (vertex) selects, by kind.
SEEDS = {
    "SV": "SELECT 'P' || p_partkey FROM part WHERE p_size >= 45",
    "SM": "SELECT 'P' || p_partkey FROM part WHERE p_partkey % 997 = 5",
    "HM": "SELECT 'HS' || s_suppkey FROM supplier WHERE s_suppkey % 97 = 3",
    "HV": "SELECT 'HC' || c_custkey FROM customer WHERE c_acctbal < -800",
}
NONE = "SELECT NULL::VARCHAR WHERE false"
BEFORE = "l.pk = r.pk AND l.seq > r.seq"


def _edges(cyclic: bool = False) -> str:
    held = "up" if cyclic else "'P' || pk"
    return f"""
ord AS (SELECT o_orderkey AS ok, o_custkey AS ck, o_orderdate AS d, row_number() OVER (ORDER BY o_orderdate, o_orderkey) AS seq FROM orders),
rel AS (SELECT ok, ok % (SELECT count(*) FROM part) AS pk, seq FROM ord),
lines AS (SELECT DISTINCT l_orderkey AS ok, l_partkey AS pk, l_suppkey AS sk, l_returnflag AS f, l_linestatus AS s FROM lineitem),
placed AS (SELECT l.*, o.ck, o.d, o.seq FROM lines l JOIN ord o USING (ok)),
used AS MATERIALIZED (SELECT l.ok, l.pk, l.sk, l.f, l.s, l.ck, l.d, r.ok AS uk, CASE WHEN r.ok IS NULL THEN 'P' || l.pk ELSE 'R' || r.ok END AS up FROM placed l ASOF LEFT JOIN rel r ON {BEFORE}),
copies AS MATERIALIZED (SELECT DISTINCT up, sk, 'C' || up || '@' || sk AS c FROM used WHERE NOT (f = 'A' AND s = 'O')),
edges AS MATERIALIZED (
  SELECT DISTINCT 'C' || up || '@' || sk AS src, CASE f WHEN 'A' THEN 'B' || ck || '/' || strftime(d, '%Y-%m') ELSE 'T' || ok END AS dst, CASE f WHEN 'N' THEN 'feeds' WHEN 'R' THEN 'tools' ELSE 'present_in' END AS label, CASE f WHEN 'N' THEN 3 ELSE 2 END AS mask FROM used WHERE NOT (f = 'A' AND s = 'O')
  UNION ALL SELECT DISTINCT {held}, 'HC' || ck, 'present_in', 3 FROM used WHERE f = 'A' AND s = 'O'
  UNION ALL SELECT 'HS' || sk, c, 'fetched_from', 2 FROM copies
  UNION ALL SELECT up, c, 'copy', 3 FROM copies
  UNION ALL SELECT DISTINCT 'HC' || ck, 'B' || ck || '/' || strftime(d, '%Y-%m'), 'hosts_env', 2 FROM ord
  UNION ALL SELECT 'B' || ck || '/' || strftime(d, '%Y-%m'), 'T' || ok, 'runs_step', 2 FROM ord
  UNION ALL SELECT 'T' || ok, 'R' || ok, 'produces', 3 FROM ord)"""


def _levels(kinds: str, tag: str = "", where: str = "true", flat: bool = False, edges: str = "edges") -> str:
    """CTEs mal and vul (with a tag): what each level reaches over edges that satisfy where."""
    both = kinds.split(",")
    top = " UNION ".join(SEEDS[k] for k in both if k in ("SM", "HM")) or NONE
    low = " UNION ".join(SEEDS[k] for k in both if k in ("SV", "HV")) or NONE
    passes = "true" if flat else "e.mask = 3"
    return f"""
mal{tag}(v) AS (SELECT * FROM ({top}) UNION SELECT e.dst FROM mal{tag} m JOIN {edges} e ON e.src = m.v WHERE {where}),
vul{tag}(v) AS (SELECT * FROM ({low}) UNION SELECT e.dst FROM vul{tag} m JOIN {edges} e ON e.src = m.v WHERE {where} AND {passes})"""


PARTS = "e.label IN ('feeds', 'produces', 'copy')"


def _status(v: str, tag: str = "") -> str:
    return f"CASE WHEN {v} IN (SELECT v FROM mal{tag}) THEN 2 WHEN {v} IN (SELECT v FROM vul{tag}) THEN 1 ELSE 0 END"


def _with(*parts: str) -> str:
    return "WITH RECURSIVE " + ",".join(parts)


def _releases(kinds: str, cyclic: bool = False, where: str = "true", flat: bool = False, having: str = "", columns: str = "order_key, status") -> str:
    inner = f"SELECT o_orderkey AS order_key, {_status(chr(39) + 'R' + chr(39) + ' || o_orderkey')} AS status FROM orders"
    return f"{_with(_edges(cyclic), _levels(kinds, where=where, flat=flat))} SELECT {columns} FROM ({inner}) {having}"


R = "'R' || o_orderkey"
BOTH = "SV,SM"


def _compare(where: str = "true", flat: bool = False) -> str:
    return f"""{_with(_edges(), _levels(BOTH), _levels(BOTH, "2", where, flat))}
SELECT full_status, other_status, count(*) AS n FROM (SELECT {_status(R)} AS full_status, {_status(R, "2")} AS other_status FROM orders) GROUP BY ALL"""


def _two(select: str, where: str = "true", flat: bool = False) -> str:
    """a: full status, b: status of the other method."""
    return f"{_with(_edges(), _levels(BOTH), _levels(BOTH, '2', where, flat))} SELECT order_key FROM (SELECT o_orderkey AS order_key, {_status(R)} AS a, {_status(R, '2')} AS b FROM orders) WHERE {select}"


def _values(columns: str, rows: list[tuple]) -> str:
    said = ", ".join("(" + ", ".join("NULL" if x is None else f"'{x}'" if isinstance(x, str) else str(x).lower() if isinstance(x, bool) else f"{x}::{'INT' if abs(x) < 10 and not isinstance(x, float) else 'BIGINT'}" for x in r) + ")" for r in rows)
    return f"SELECT * FROM (VALUES {said}) AS t({columns})"


# The worked example once for each conversation; its facts hold where flagged.
INSTANCES = "WITH each AS (SELECT conv_id, coalesce(sum(length(text)) % 2 = 1, false) AS flagged FROM conversations GROUP BY conv_id)"


def _case(rows: list[tuple]) -> str:
    said = ", ".join(f"({t}::BIGINT, {s}, '{a}', '{b}', '{c}', '{d}')" for t, s, a, b, c, d in rows)
    held = ", ".join(f"CASE WHEN flagged THEN {x} ELSE '' END AS {x}" for x in ("sv", "sm", "hv", "hm"))
    return f"{INSTANCES} SELECT conv_id, target, CASE WHEN flagged THEN status ELSE 0 END AS status, {held} FROM each, (VALUES {said}) AS t(target, status, sv, sm, hv, hm)"


# Each rule's printed rows; what every order's lines hand to them.
PRINTED = {"host": "000 101 202 022 122 222", "step1": "000 100 202 011 111 212 022 122 222", "env": "000 100 202 010 110 212 022 122 222", "step2": "000 101 202 022 122 222"}
USED_LEVELS = f"""WITH {", ".join(f"{name} AS (SELECT * FROM (VALUES " + ", ".join(f"({a}, {b}, {c})" for a, b, c in rows.split()) + ") AS t(a, b, result))" for name, rows in PRINTED.items())},
line AS (SELECT l_orderkey AS ok, CASE l_returnflag WHEN 'R' THEN 'tool' WHEN 'N' THEN 'fed' ELSE CASE WHEN l_linestatus = 'O' THEN 'held' ELSE 'present' END END AS use, CASE WHEN p_partkey % 997 = 5 THEN 2 WHEN p_size >= 45 THEN 1 ELSE 0 END AS level, l_suppkey % 97 = 3 AS breached FROM lineitem JOIN part ON p_partkey = l_partkey),
used AS (SELECT ok, coalesce(max(level) FILTER (use = 'held'), 0) AS held, CASE WHEN bool_or(use = 'held' AND breached) THEN 2 ELSE 0 END AS breach, coalesce(max(level) FILTER (use = 'tool'), 0) AS tool, coalesce(max(level) FILTER (use = 'fed'), 0) AS fed, coalesce(max(level) FILTER (use = 'present'), 0) AS present FROM line GROUP BY ok),
one AS (SELECT u.*, h.result AS on_host, s.result AS first FROM used u JOIN host h ON h.a = held AND h.b = breach JOIN step1 s ON s.a = tool AND s.b = fed),
two AS (SELECT o.*, v.result AS around FROM one o JOIN env v ON v.a = on_host AND v.b = present)"""


def _rule(name: str, a: str, b: str) -> str:
    return f"{USED_LEVELS} SELECT ok AS order_key, r.a, r.b, r.result FROM two JOIN {name} r ON r.a = two.{a} AND r.b = two.{b}"


EXAMPLE_EDGES = "4 present_in 5,3 present_in 7,5 hosts_env 7,7 runs_step 8,2 tools 8,6 feeds 8,8 produces 9,8 produces 10,9 published_to 11,10 published_to 11,1 fetched_from 2,1 fetched_from 6"
EXAMPLE_TYPES = {1: "host", 2: "artifact", 3: "artifact", 4: "artifact", 5: "host", 6: "artifact", 7: "env", 8: "step", 9: "artifact", 10: "artifact", 11: "host"}
_EDGE_ROWS = [x.split() for x in EXAMPLE_EDGES.split(",")]

EX_VERTICES = f"{INSTANCES} SELECT conv_id, vid, vtype, CASE WHEN flagged THEN status ELSE 0 END AS status FROM each, (VALUES " + ", ".join(f"({v}::BIGINT, '{t}', {2 if v in (4, 5, 7, 8, 9, 10) else 0})" for v, t in EXAMPLE_TYPES.items()) + ") AS t(vid, vtype, status)"

COPY_EDGES = """
doc AS (SELECT doc_id, source, sha256(text) AS akey FROM documents),
pair AS (SELECT *, lag(doc_id) OVER w AS previous, lag(source) OVER w AS previous_source FROM doc WINDOW w AS (PARTITION BY akey ORDER BY doc_id)),
linked AS MATERIALIZED (SELECT * FROM pair WHERE previous IS NOT NULL),
held AS MATERIALIZED (SELECT DISTINCT previous_source AS host, akey, previous AS p FROM linked),
copied AS MATERIALIZED (SELECT DISTINCT l.previous_source AS host, h.p, l.doc_id AS c FROM linked l JOIN held h ON h.host = l.previous_source AND h.akey = l.akey AND h.p <> l.doc_id),
edges AS MATERIALIZED (SELECT 'D' || p AS src, 'D' || c AS dst, 3 AS mask FROM copied UNION ALL SELECT 'H' || previous_source, 'D' || doc_id, 2 FROM linked),
bad AS (SELECT doc_id FROM labels WHERE toxic = 1 UNION SELECT doc_id FROM documents WHERE doc_id % 37 = 5),
mal(v) AS (SELECT 'D' || doc_id FROM bad UNION SELECT e.dst FROM mal m JOIN edges e ON e.src = m.v),
vul(v) AS (SELECT 'D' || doc_id FROM labels WHERE quality = 0 UNION SELECT e.dst FROM vul m JOIN edges e ON e.src = m.v WHERE e.mask = 3),
context AS (SELECT host AS source, c AS doc_id, max(CASE WHEN 'D' || p IN (SELECT v FROM mal) THEN 2 WHEN 'D' || p IN (SELECT v FROM vul) THEN 1 ELSE 0 END) AS context_status FROM copied GROUP BY host, c)"""

CHAIN = """WITH said AS (SELECT conv_id, turn, max(CASE WHEN length(text) % 41 = 0 THEN 2 WHEN length(text) % 17 = 0 THEN 1 ELSE 0 END) AS own FROM conversations WHERE role <> 'system' GROUP BY ALL),
sys AS (SELECT conv_id, turn, max(CASE WHEN length(text) % 41 = 0 THEN 2 WHEN length(text) % 17 = 0 THEN 1 ELSE 0 END) AS own FROM conversations WHERE role = 'system' GROUP BY ALL),
lifted AS (SELECT DISTINCT conv_id FROM sys WHERE own = 2),
run AS (SELECT conv_id, turn, max(own) OVER w AS upto, row_number() OVER w AS k FROM said WINDOW w AS (PARTITION BY conv_id ORDER BY turn))
SELECT conv_id, turn, CASE WHEN k > 1 AND conv_id IN (SELECT conv_id FROM lifted) THEN 2 ELSE upto END AS status FROM run
UNION ALL SELECT conv_id, turn, own FROM sys"""

PLACED = f"placed_releases AS (SELECT r_name, n_name, {_status(R)} AS status FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)"
SERVED = "served AS (SELECT s_suppkey AS supplier_key, s_nationkey, count(c.c) AS n FROM supplier LEFT JOIN (SELECT * FROM copies WHERE c IN (SELECT v FROM mal)) c ON c.sk = s_suppkey GROUP BY ALL)"
FIRST8 = "pick AS (SELECT o_orderkey AS ok FROM orders ORDER BY o_orderkey LIMIT 8)"
BEHIND = "behind(t, v) AS (SELECT ok, 'R' || ok FROM pick UNION SELECT b.t, e.src FROM behind b JOIN edges e ON e.dst = b.v)"
MEMBERS = """members AS (
  SELECT t, CASE WHEN v LIKE 'H%' THEN CASE WHEN v IN (SELECT v FROM mal) THEN 'HM' ELSE 'HV' END ELSE CASE WHEN v IN (SELECT v FROM mal) THEN 'SM' ELSE 'SV' END END AS cls, v
  FROM behind WHERE v NOT LIKE 'T%' AND v NOT LIKE 'B%' AND (v IN (SELECT v FROM mal) OR v IN (SELECT v FROM vul))
  UNION SELECT b.t, 'HM', 'HS' || c.sk FROM behind b JOIN copies c ON c.c = b.v WHERE c.up IN (SELECT v FROM mal))"""
THREE = "SV,SM,HV"
VERDICTS = _with(_edges(), _levels(THREE), FIRST8, BEHIND, MEMBERS)
AUTHORITY = "split_part(split_part(split_part(regexp_extract(url, '^[a-z]+://([^/?#]*)', 1), '@', -1), ':', 1), '/', 1)"
FEED = """feed AS (SELECT event_id, ts, CASE WHEN event_type = 'error' THEN 'SV' WHEN event_type = 'signup' AND value > 150 THEN 'HM' END AS kind, CASE WHEN event_type = 'error' THEN user_id % (SELECT count(*) FROM part) ELSE user_id % (SELECT count(*) FROM supplier) END AS key FROM events)"""
CODE = "CASE WHEN v LIKE 'P%' THEN 1 WHEN v LIKE 'R%' THEN 2 WHEN v LIKE 'C%' THEN 3 WHEN v LIKE 'T%' THEN 4 WHEN v LIKE 'B%' THEN 5 WHEN v LIKE 'HS%' THEN 6 ELSE 7 END"
NODES = "nodes AS MATERIALIZED (SELECT 'P' || p_partkey AS v FROM part UNION ALL SELECT 'R' || o_orderkey FROM orders UNION ALL SELECT 'T' || o_orderkey FROM orders UNION ALL SELECT c FROM copies UNION ALL SELECT DISTINCT 'B' || ck || '/' || strftime(d, '%Y-%m') FROM ord UNION ALL SELECT 'HS' || s_suppkey FROM supplier UNION ALL SELECT 'HC' || c_custkey FROM customer)"
TYPE = "CASE WHEN v LIKE 'T%' THEN 'step' WHEN v LIKE 'B%' THEN 'env' WHEN v LIKE 'H%' THEN 'host' ELSE 'artifact' END"
RAW = "raw AS (SELECT src, dst, label FROM edges WHERE label <> 'copy' UNION ALL SELECT up, 'HS' || sk, 'published_to' FROM copies)"
LAST = "last_release AS (SELECT arg_max('R' || ok, seq) AS v FROM ord)"
MISSING = "mal(v) AS (SELECT DISTINCT 'HS0' FROM copies WHERE sk = 0 UNION SELECT e.dst FROM mal m JOIN edges e ON e.src = m.v WHERE NOT (e.label = 'copy' AND e.dst LIKE '%@0'))"

TIMED = f"{_with(_edges())}, active AS (SELECT DISTINCT 'HS' || u.sk AS src, 'C' || u.up || '@' || u.sk AS dst FROM used u JOIN lineitem l ON l_orderkey = u.ok AND l_partkey = u.pk AND l_suppkey = u.sk AND l_returnflag = u.f AND l_linestatus = u.s WHERE NOT (u.f = 'A' AND u.s = 'O') AND u.sk % 97 = 3 AND l_shipdate >= TIMESTAMP '1995-01-01' + to_days((20 * u.sk)::INT) AND l_shipdate < TIMESTAMP '1995-01-01' + to_days((20 * u.sk + 90)::INT)), timed AS MATERIALIZED (SELECT e.* FROM edges e WHERE e.src NOT IN ({SEEDS['HM']}) OR (e.src, e.dst) IN (SELECT src, dst FROM active))"
WEEK = """malw{w}(v) AS (SELECT 'HS' || key FROM feed WHERE kind = 'HM' AND ts < TIMESTAMP '2024-01-01' + to_days({after}) UNION SELECT e.dst FROM malw{w} m JOIN edges e ON e.src = m.v),
vulw{w}(v) AS (SELECT 'P' || key FROM feed WHERE kind = 'SV' AND ts < TIMESTAMP '2024-01-01' + to_days({after}) UNION SELECT e.dst FROM vulw{w} m JOIN edges e ON e.src = m.v WHERE e.mask = 3)"""
FOUR = "SV,SM,HV,HM"
AUDITED = f"""{_with(_edges(), _levels(FOUR))}, pick AS (SELECT 'build' AS kind, c_custkey AS k, 'HC' || c_custkey AS v, c_nationkey AS nk FROM customer UNION ALL SELECT 'storage', s_suppkey, 'HS' || s_suppkey, s_nationkey FROM supplier),
bad AS MATERIALIZED (SELECT kind, k, v, nk, {_status('v')} AS status FROM pick WHERE {_status('v')} > 0),
hit(s, v) AS (SELECT v, v FROM bad UNION SELECT h.s, e.dst FROM hit h JOIN edges e ON e.src = h.v),
per AS (SELECT s, count(*) AS n FROM hit WHERE v LIKE 'R%' GROUP BY s),
audited AS (SELECT kind, k, n_name AS nation, r_name AS region, status, coalesce(n, 0) AS n FROM bad LEFT JOIN per ON s = v JOIN nation ON n_nationkey = nk JOIN region ON r_regionkey = n_regionkey)"""
SCORED = f"""{_with(_edges())}, weighed AS MATERIALIZED (SELECT src, dst, mask, CASE label WHEN 'produces' THEN 0.9::DOUBLE WHEN 'fetched_from' THEN round(1.0::DOUBLE - least(0.5::DOUBLE, greatest(0.0::DOUBLE, s_acctbal / 20000)), 6) ELSE 1.0::DOUBLE END AS w FROM edges LEFT JOIN supplier ON label = 'fetched_from' AND src = 'HS' || s_suppkey),
start AS (SELECT v, max(s)::DOUBLE AS s FROM (SELECT 'P' || p_partkey AS v, 1 AS s FROM part WHERE p_size >= 45 UNION ALL SELECT 'P' || p_partkey, 2 FROM part WHERE p_partkey % 997 = 5) GROUP BY v),
hit(v, s) USING KEY (v) AS (SELECT v, s FROM start UNION SELECT e.dst, max(round(CASE WHEN h.s > 1 THEN 1 + (h.s - 1) * w ELSE h.s * w END, 9)) FROM hit h JOIN weighed e ON e.src = h.v LEFT JOIN recurring.hit o ON o.v = e.dst WHERE h.s > 1 OR e.mask = 3 GROUP BY e.dst, o.s HAVING max(round(CASE WHEN h.s > 1 THEN 1 + (h.s - 1) * w ELSE h.s * w END, 9)) > coalesce(o.s, 0))
SELECT o_orderkey AS order_key, round(coalesce(s, 0.0), 6) AS score FROM orders LEFT JOIN hit ON v = 'R' || o_orderkey"""
# By hand from the rules: the sets behind a part, two hosts, an environment and a step.
ELEMENTS = "SELECT * FROM (VALUES " + ", ".join(f"('{c}', {t}::BIGINT, {s}, '{a}', '{b}', '{d}', '{e}')" for c, t, s, a, b, d, e in (
    ("uc1", 4, 1, "4", "", "", ""), ("uc1", 5, 1, "4", "", "5", ""), ("uc1", 7, 0, "3,4", "", "5", ""), ("uc1", 8, 0, "2,3,4", "", "5", ""), ("uc1", 11, 0, "", "", "", ""),
    ("uc2", 4, 0, "", "", "", ""), ("uc2", 5, 0, "", "", "", ""), ("uc2", 7, 0, "", "", "", ""), ("uc2", 8, 1, "6", "", "", ""), ("uc2", 11, 0, "", "", "", ""),
    ("uc3", 4, 2, "", "4", "", ""), ("uc3", 5, 2, "", "4", "", "5"), ("uc3", 7, 2, "", "4", "", "5"), ("uc3", 8, 2, "", "4", "", "5"), ("uc3", 11, 0, "", "", "", ""),
)) + ") AS t(use_case, target, status, sv, sm, hv, hm)"

ORACLES: dict[str, str] = {
    "ex_vertices": EX_VERTICES,
    "ex_validate": f"{INSTANCES} SELECT conv_id, label, CASE WHEN flagged AND label = 'feeds' THEN 'host' ELSE src_type END AS src_type, dst_type, NOT (flagged AND label = 'feeds') AS legal FROM each, (VALUES " + ", ".join(f"('{label}', '{EXAMPLE_TYPES[int(s)]}', '{EXAMPLE_TYPES[int(d)]}')" for s, label, d in _EDGE_ROWS) + ") AS t(label, src_type, dst_type)",
    "uc1_example": _case([(9, 0, "2,3,4", "", "5", ""), (10, 0, "2,3,4", "", "5", "")]),
    "uc2_example": _case([(9, 1, "6,9", "", "", ""), (10, 1, "6,10", "", "", "")]),
    "uc3_example": _case([(9, 2, "", "4,9", "", "5"), (10, 2, "", "4,10", "", "5")]),
    "uc3_union": f"{INSTANCES} SELECT CASE WHEN count(*) > 0 THEN 2 ELSE 0 END AS status, '' AS sv, coalesce(string_agg(v, ',' ORDER BY v) FILTER (v % 16 <> 5), '') AS sm, '' AS hv, coalesce(string_agg(v, ',' ORDER BY v) FILTER (v % 16 = 5), '') AS hm FROM (SELECT conv_id * 16 + n AS v FROM each, (VALUES (4), (5), (9), (10)) AS t(n) WHERE flagged)",
    "rules_host": _rule("host", "held", "breach"),
    "rules_step1": _rule("step1", "tool", "fed"),
    "rules_env": _rule("env", "on_host", "present"),
    "rules_step2": _rule("step2", "first", "around"),
    "build_vertices": f"{_with(_edges(), NODES)} SELECT {TYPE} AS vtype, count(*) AS n FROM nodes GROUP BY ALL",
    "build_edges_by_label": f"{_with(_edges(), RAW)} SELECT label, count(*) AS n FROM raw GROUP BY ALL",
    "edges_by_label": f"{_with(_edges())} SELECT label, count(DISTINCT dst) AS steps, count(DISTINCT src) AS artifacts FROM edges WHERE label IN ('feeds', 'tools') GROUP BY ALL",
    "build_validate": "SELECT NULL::VARCHAR AS reason, 0::BIGINT AS n WHERE false",
    "asof_release": f"{_with(_edges())} SELECT DISTINCT ok AS order_key, pk AS part_key, uk AS used_order_key FROM used",
    "compiled_edges": f"{_with(_edges())} SELECT label, mask, count(*) AS n FROM edges GROUP BY ALL",
    "uc1_safe_despite_vulnerable_upstream": f"{_with(_edges(), _levels('SV'))}, weak(v) AS (SELECT v FROM vul WHERE v LIKE 'P%' OR v LIKE 'R%' OR v LIKE 'C%' UNION SELECT e.dst FROM weak w JOIN edges e ON e.src = w.v) SELECT o_orderkey AS order_key FROM orders WHERE {_status(R)} = 0 AND {R} IN (SELECT v FROM weak)",
    "uc2_vulnerable_releases": _releases("SV", having="WHERE status > 0"),
    "uc2_patch_candidates": f"{_with(_edges())}, hit(s, v) AS (SELECT p_partkey, 'P' || p_partkey FROM part WHERE p_size >= 45 UNION SELECT h.s, e.dst FROM hit h JOIN edges e ON e.src = h.v WHERE e.mask = 3), n AS (SELECT p_partkey AS part_key, count(h.v) AS n_releases FROM part LEFT JOIN hit h ON h.s = p_partkey AND h.v LIKE 'R%' WHERE p_size >= 45 GROUP BY ALL) SELECT part_key, n_releases, rank() OVER (ORDER BY n_releases DESC)::INT AS rank FROM n",
    "uc3_malicious_releases": _releases(BOTH, having="WHERE status = 2", columns="order_key"),
    "uc3_missed_by_parts_only": _two("a = 2 AND b < 2", PARTS, True),
    "uc3_host_path_only": _two("a = 2 AND b < 2", "e.label <> 'hosts_env'"),
    "status_releases": _releases(BOTH),
    "status_steps": f"{_with(_edges(), _levels(BOTH))} SELECT o_orderkey AS order_key, {_status(chr(39) + 'T' + chr(39) + ' || o_orderkey')} AS status FROM orders",
    "status_envs": f"{_with(_edges(), _levels(BOTH))} SELECT DISTINCT ck AS cust_key, ((year(d) - 1970) * 12 + month(d) - 1)::INT AS month, {_status(chr(39) + 'B' + chr(39) + ' || ck || ' + chr(39) + '/' + chr(39) + ' || strftime(d, ' + chr(39) + '%Y-%m' + chr(39) + ')')} AS status FROM ord",
    "status_hosts": f"{_with(_edges(), _levels('SV,SM,HV,HM'))} SELECT 'build' AS kind, c_custkey AS host_key, {_status(chr(39) + 'HC' + chr(39) + ' || c_custkey')} AS status FROM customer UNION ALL SELECT 'storage', s_suppkey, {_status(chr(39) + 'HS' + chr(39) + ' || s_suppkey')} FROM supplier",
    "status_copies": f"{_with(_edges(), _levels(BOTH))} SELECT CASE WHEN up LIKE 'P%' THEN 'part' ELSE 'release' END AS artifact, substr(up, 2)::BIGINT AS artifact_key, sk AS supp_key, {_status('c')} AS status FROM copies",
    "status_by_type": f"{_with(_edges(), _levels(BOTH), NODES)} SELECT {TYPE} AS vtype, {_status('v')} AS status, count(*) AS n FROM nodes GROUP BY ALL",
    "breached_mirror": _releases("SV,HM"),
    "web_hosts": f"SELECT {AUTHORITY} AS authority, count(*) AS n_pages FROM pages GROUP BY ALL",
    "web_breached_mirror": f"SELECT page_id, {AUTHORITY} AS authority, CASE WHEN {AUTHORITY} LIKE '%cheap-pills%' OR length({AUTHORITY}) % 11 = 0 THEN 2 ELSE 0 END AS status FROM pages",
    "copy_pairs": f"{_with(COPY_EDGES)} SELECT doc_id, source, previous, previous_source FROM linked",
    "copy_context_hosts": f"{_with(COPY_EDGES)} SELECT source, doc_id, context_status FROM context",
    "copy_mixed_hosts": f"{_with(COPY_EDGES)} SELECT source, count(*) FILTER (context_status = 2) AS tainted, count(*) FILTER (context_status < 2) AS clean FROM context GROUP BY ALL HAVING tainted > 0 AND clean > 0",
    "chain_status": CHAIN,
    "levels_status": CHAIN,
    "two_phase_status": _releases(BOTH),
    "retract_far_status": _releases("SV"),
    "recursive_example": EX_VERTICES,
    "recursive_chain_status": CHAIN,
    "takedown_list": f"{_with(_edges(), _levels(BOTH))} SELECT sk AS supplier_key, count(DISTINCT up) AS n_malicious FROM copies WHERE up IN (SELECT v FROM mal) GROUP BY ALL",
    "audit_hosts_topk": f"{AUDITED} SELECT kind, k AS host_key, nation, region, status, n AS n_affected, rank() OVER (ORDER BY n DESC)::INT AS rank FROM (SELECT * FROM audited ORDER BY n DESC, kind, k LIMIT 20)",
    "audit_by_nation": f"{AUDITED} SELECT region, nation, kind, status, count(*) AS n_hosts, max(n) AS most_affected FROM audited GROUP BY ALL",
    "verdict_sample": f"{VERDICTS} SELECT ok AS order_key, {_status(chr(39) + 'R' + chr(39) + ' || ok')} AS status, " + ", ".join(f"(SELECT count(*) FROM members m WHERE m.t = ok AND cls = '{c.upper()}')::INT AS n_{c}" for c in ("sv", "sm", "hv", "hm")) + " FROM pick",
    "verdict_arrays": f"{VERDICTS} SELECT ok AS order_key, (SELECT count(DISTINCT v) FROM members m WHERE m.t = ok AND cls IN ('SV', 'SM'))::INT AS n_flagged, coalesce((SELECT string_agg(k, ',' ORDER BY k) FROM (SELECT DISTINCT substr(v, 2)::BIGINT AS k FROM members m WHERE m.t = ok AND v LIKE 'P%')), '') AS parts, coalesce((SELECT string_agg(k, ',' ORDER BY k) FROM (SELECT DISTINCT substr(v, 3)::BIGINT AS k FROM members m WHERE m.t = ok AND v LIKE 'HC%' ORDER BY k LIMIT 5)), '') AS first_hosts FROM pick",
    "verdict_long": f"{VERDICTS} SELECT t AS order_key, cls, count(*) AS n FROM members GROUP BY ALL",
    "unknown_refs": f"{_with(_edges(), MISSING)} SELECT o_orderkey AS order_key FROM orders WHERE {R} IN (SELECT v FROM mal)",
    "cmp_parts_only": _compare(PARTS, True),
    "cmp_flat": _compare(flat=True),
    "cmp_hostblind": _compare("e.label <> 'hosts_env'"),
    "cmp_envblind": _compare("e.label NOT IN ('hosts_env', 'runs_step')"),
    "setop_flagged_both": _two("a > 0 AND b > 0", PARTS, True),
    "setop_only_flat": _two("b > 0 AND a = 0", flat=True),
    "sca_parts_status": _releases(BOTH, where=PARTS, flat=True),
    "flat_status": _releases(BOTH, flat=True),
    "attack_tree_nodes": f"{_with(_edges(), LAST)}, tree(v, depth) AS (SELECT v, 0 FROM last_release UNION SELECT e.src, t.depth + 1 FROM tree t JOIN edges e ON e.dst = t.v WHERE t.depth < 6), least AS (SELECT v, min(depth) AS depth FROM tree GROUP BY ALL) SELECT DISTINCT a.v AS node, e.dst AS parent, a.depth::INT AS depth, 'OR' AS gate, a.v IN ({SEEDS['SM']}) AS leaf FROM least a JOIN edges e ON e.src = a.v JOIN least b ON b.v = e.dst AND b.depth < 6 UNION ALL SELECT v, NULL, 0, 'OR', false FROM last_release",
    "blast_radius": f"{_with(_edges())}, seed(k, key, v) AS (SELECT 'part', p_partkey, 'P' || p_partkey FROM part WHERE p_partkey % 997 = 5 UNION ALL SELECT 'supplier', s_suppkey, 'HS' || s_suppkey FROM supplier WHERE s_suppkey % 97 = 3), hit(s, v) AS (SELECT v, v FROM seed UNION SELECT h.s, e.dst FROM hit h JOIN edges e ON e.src = h.v) SELECT k AS kind, key AS seed_key, (SELECT count(*) FROM hit h WHERE h.s = seed.v AND h.v LIKE 'R%') AS n_products FROM seed",
    "cyc_status": _releases(BOTH, cyclic=True),
    "semi_naive_status": _releases(BOTH),
    "contracted_status": _releases(BOTH),
    "jumping_status": _releases(BOTH),
    "finisher_status": _releases(BOTH),
    "degree_hist": f"{_with(_edges(), NODES, RAW)} SELECT degree, count(*) AS n FROM (SELECT v, count(raw.dst) AS degree FROM nodes LEFT JOIN raw ON raw.dst = v GROUP BY v) GROUP BY ALL",
    "reach_count": f"{_with(_edges())}, hit(s, v, hops) USING KEY (s, v) AS (SELECT p_partkey, 'P' || p_partkey, 0 FROM part WHERE p_partkey % 997 = 5 UNION SELECT h.s, e.dst, min(h.hops) + 1 FROM hit h JOIN edges e ON e.src = h.v LEFT JOIN recurring.hit o ON o.s = h.s AND o.v = e.dst WHERE o.v IS NULL GROUP BY h.s, e.dst) SELECT s AS part_key, count(*) AS n, max(hops)::BIGINT AS hops FROM hit GROUP BY ALL",
    "components_small": f"{_with(COPY_EDGES)}, both_ways AS (SELECT src, dst FROM edges UNION SELECT dst, src FROM edges), near(v, r) AS (SELECT DISTINCT src, src FROM both_ways UNION SELECT n.v, b.dst FROM near n JOIN both_ways b ON b.src = n.r), comp AS (SELECT v, min(r) AS c FROM near GROUP BY v), every AS (SELECT 'D' || doc_id AS v FROM documents UNION SELECT DISTINCT 'H' || source FROM documents), sized AS (SELECT coalesce(c, e.v) AS c, count(*) AS size FROM every e LEFT JOIN comp USING (v) GROUP BY ALL) SELECT size, count(*) AS n FROM sized GROUP BY ALL",
    "anti_roots": "SELECT p_partkey AS part_key FROM part WHERE p_partkey NOT IN (SELECT o_orderkey % (SELECT count(*) FROM part) FROM orders)",
    "graph_roots": f"{_with(_edges(), NODES, RAW)} SELECT kind, ({CODE})::INT AS node_code, count(*) AS n FROM (SELECT 'root' AS kind, v FROM nodes WHERE v NOT IN (SELECT dst FROM raw) UNION ALL SELECT 'sink', v FROM nodes WHERE v NOT IN (SELECT src FROM raw)) GROUP BY ALL",
    "usecase_replay": f"{_with(_edges(), _levels('SV', '1'), _levels('SV,SM', '2'), _levels('SV,SM,HM', '3'))} SELECT step::INT AS step, status, count(*) AS n FROM (" + " UNION ALL ".join(f"SELECT {i} AS step, {_status(R, str(i))} AS status FROM orders" for i in (1, 2, 3)) + ") GROUP BY ALL",
    "disclosure_replay": f"{_with(_edges(), FEED, *[WEEK.format(w=w, after=7 * (w + 1)) for w in range(5)])} SELECT step::INT AS step, status, count(*) AS n FROM (" + " UNION ALL ".join(f"SELECT {w + 1} AS step, {_status(R, f'w{w}')} AS status FROM orders" for w in range(5)) + ") GROUP BY ALL",
    "temporal_gain": f"{TIMED}, {_levels('SV,HM', 't', edges='timed')}, {_levels('SV,HM')} SELECT plain_status, temporal_status, count(*) AS n FROM (SELECT {_status(R)} AS plain_status, {_status(R, 't')} AS temporal_status FROM orders) GROUP BY ALL",
    "scored_releases": SCORED,
    "verdict_elements": ELEMENTS,
    "verdict_host_in_context": "SELECT * FROM (VALUES (11::BIGINT, 12::BIGINT, 2), (11, 13, 0)) AS t(target, artifact, status)",
    "topo_levels": f"{_with(_edges(), NODES)}, lev(v, level) USING KEY (v) AS (SELECT v, 0 FROM nodes UNION SELECT e.dst, max(l.level) + 1 FROM lev l JOIN edges e ON e.src = l.v LEFT JOIN recurring.lev o ON o.v = e.dst GROUP BY e.dst, o.level HAVING max(l.level) + 1 > coalesce(o.level, -1)) SELECT level::BIGINT AS level, count(*) AS n FROM lev GROUP BY ALL",
    "stream_replay_status": f"{_with(_edges(), FEED)}, mal(v) AS (SELECT 'HS' || key FROM feed WHERE kind = 'HM' UNION SELECT e.dst FROM mal m JOIN edges e ON e.src = m.v), vul(v) AS (SELECT 'P' || key FROM feed WHERE kind = 'SV' UNION SELECT e.dst FROM vul m JOIN edges e ON e.src = m.v WHERE e.mask = 3) SELECT o_orderkey AS order_key, {_status(R)} AS status FROM orders",
    "temporal_status": f"{TIMED}, {_levels('SV,HM', edges='timed')} SELECT o_orderkey AS order_key, {_status(R)} AS status FROM orders",
    "retract_status": _releases("SV"),
    "win_tumbling": "SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, time_bucket(INTERVAL 1 DAY, ts) + INTERVAL 1 DAY AS stop, event_type, count(*) AS n FROM events GROUP BY ALL",
    "win_sliding": "WITH d AS (SELECT time_bucket(INTERVAL 1 DAY, ts) AS b, event_type FROM events), w AS (SELECT b AS start, event_type FROM d UNION ALL SELECT b - INTERVAL 1 DAY, event_type FROM d) SELECT start, start + INTERVAL 2 DAY AS stop, event_type, count(*) AS n FROM w GROUP BY ALL",
    "win_session": "WITH g AS (SELECT *, CASE WHEN ts > lag(ts) OVER w + INTERVAL 6 HOUR OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT min(ts) AS start, max(ts) + INTERVAL 6 HOUR AS stop, user_id, count(*) AS n FROM s GROUP BY user_id, k",
    "rollup_region_status": f"{_with(_edges(), _levels(BOTH), PLACED)} SELECT r_name, n_name, status, count(*) AS n, grouping(r_name, n_name, status)::INT AS level FROM placed_releases GROUP BY ROLLUP (r_name, n_name, status)",
    "gsets_status": f"{_with(_edges(), _levels(BOTH), PLACED)} SELECT r_name, n_name, status, count(*) AS n, grouping(r_name, n_name, status)::INT AS level FROM placed_releases GROUP BY GROUPING SETS ((r_name, status), (n_name, status), (status))",
    "pivot_nation_status": f"{_with(_edges(), _levels(BOTH), PLACED)} SELECT n_name, count(*) FILTER (status = 0) AS safe, count(*) FILTER (status = 1) AS vulnerable, count(*) FILTER (status = 2) AS malicious FROM placed_releases GROUP BY ALL",
    "cube_type_role_status": f"{_with(_edges(), _levels(BOTH))}, uses AS (SELECT label, CASE WHEN src LIKE 'P%' THEN 'part' ELSE 'copy' END AS kind, {_status('src')} AS status FROM edges WHERE label IN ('feeds', 'tools', 'present_in')) SELECT label, kind, status, count(*) AS n, grouping(label, kind, status)::INT AS level FROM uses GROUP BY CUBE (label, kind, status)",
    "window_host_rank": f"{_with(_edges(), _levels(BOTH), SERVED)} SELECT supplier_key, n, rank() OVER r::INT AS rank, dense_rank() OVER r::INT AS dense_rank, ntile(4) OVER (PARTITION BY s_nationkey ORDER BY n DESC, supplier_key)::INT AS quarter, round(percent_rank() OVER r, 6) AS share FROM served WINDOW r AS (PARTITION BY s_nationkey ORDER BY n DESC)",
    "window_build_gap": "SELECT o_orderkey AS order_key, date_diff('day', lag(o_orderdate) OVER w, o_orderdate)::INT AS days, lead(o_orderkey) OVER w AS next_order_key FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)",
    "window_running_status": f"{_with(_edges(), _levels(BOTH))} SELECT o_orderkey AS order_key, max({_status(R)}) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING) AS worst FROM orders",
    "window_range_incidents": f"WITH {FEED} SELECT event_id, key AS supplier_key, count(*) OVER (PARTITION BY key ORDER BY ts RANGE BETWEEN INTERVAL 30 DAY PRECEDING AND CURRENT ROW) AS n FROM feed WHERE kind = 'HM'",
    "topk_parts_per_brand": f"{_with(_edges(), _levels('SV'))}, weak AS (SELECT o_orderkey % (SELECT count(*) FROM part) AS pk, count(*) AS n FROM orders WHERE {_status(R)} = 1 GROUP BY ALL) SELECT p_brand, p_partkey AS part_key, n, row_number() OVER w::INT AS place FROM part JOIN weak ON pk = p_partkey WINDOW w AS (PARTITION BY p_brand ORDER BY n DESC, p_partkey) QUALIFY place <= 3",
    "overlap_exposure": "SELECT s_suppkey AS supplier_key, count(*) AS n_lines FROM supplier JOIN lineitem ON l_suppkey = s_suppkey WHERE l_shipdate >= TIMESTAMP '1995-01-01' + to_days((20 * s_suppkey)::INT) AND l_shipdate < TIMESTAMP '1995-01-01' + to_days((20 * s_suppkey + 90)::INT) GROUP BY ALL",
    "advisory_match": "SELECT p_partkey AS part_key, lo, hi FROM part JOIN (VALUES ('Brand#1', 10, 20), ('Brand#2', 1, 5), ('Brand#3', 40, 50), ('Brand#11', 10, 20), ('Brand#23', 1, 15), ('Brand#45', 30, 50)) AS a(b, lo, hi) ON b = p_brand AND p_size BETWEEN lo AND hi",
    "semi_exposed_orders": "SELECT o_orderkey AS order_key FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem JOIN part ON l_partkey = p_partkey WHERE p_size >= 45)",
    "version_compare": "WITH r AS (SELECT o_orderkey AS order_key, o_orderkey % (SELECT count(*) FROM part) AS pk, o_orderdate FROM orders), v AS (SELECT order_key, row_number() OVER (PARTITION BY pk ORDER BY o_orderdate, order_key) AS k, p_size FROM r JOIN part ON p_partkey = pk) SELECT order_key, '1.' || k || '.' || p_size AS version, CASE WHEN (k, p_size) < (5, 0) THEN -1 WHEN (k, p_size) > (5, 0) THEN 1 ELSE 0 END AS order_to_1_5 FROM v",
    "name_match": "WITH w AS (SELECT p_partkey, unnest(string_split(lower(p_name), ' ')) AS own FROM part), g AS (SELECT * FROM (VALUES ('rng', 1), ('wiget', 1), ('bolts', 1), ('blu', 1), ('smal', 1), ('gear', 2)) AS t(word, most)) SELECT p_partkey AS part_key, word, min(levenshtein(own, word))::INT AS edits FROM w JOIN g ON levenshtein(own, word) <= most GROUP BY ALL",
    "env_months": "SELECT date_trunc('month', o_orderdate)::TIMESTAMP AS month, count(DISTINCT o_custkey) AS n_envs, count(*) AS n_steps FROM orders GROUP BY ALL",
    "props_json": "SELECT event_type, sum((props ->> '$.k')::INT)::BIGINT AS total, count(*) AS n FROM events GROUP BY ALL",
    "seed_map": "SELECT p_partkey AS part_key, concat_ws(',', CASE WHEN p_partkey % 997 = 5 THEN 'SM' END, CASE WHEN p_size >= 45 THEN 'SV' END) AS kinds, CASE WHEN p_partkey % 997 = 5 THEN 1 ELSE 0 END AS is_malicious FROM part WHERE p_size >= 45 OR p_partkey % 997 = 5",
    "scan_counts": " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")),
    "embedding_norms": "SELECT label, len(embedding)::INT AS d, count(*) AS n, round(avg(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))), 4) AS mean_square FROM embeddings GROUP BY ALL",
    "exposure_percentiles": "WITH per AS (SELECT l_orderkey, count(DISTINCT l_partkey) AS n FROM lineitem GROUP BY ALL) SELECT o_orderstatus, quantile_cont(n, 0.5) AS median, quantile_cont(n, 0.9) AS p90, max(n) AS most FROM orders JOIN per ON l_orderkey = o_orderkey GROUP BY ALL",
    "export_verdict_json": f"{VERDICTS} SELECT '{{\"order_key\":' || ok || ',\"status\":' || {_status(chr(39) + 'R' + chr(39) + ' || ok')} || ',\"n_sm\":' || (SELECT count(*) FROM members m WHERE m.t = ok AND cls = 'SM') || '}}' AS line FROM pick",
    "udf_status_name": f"{_with(_edges(), _levels(BOTH))} SELECT CASE status WHEN 0 THEN 'safe' WHEN 1 THEN 'vulnerable' ELSE 'malicious' END AS name, status AS level, count(*) AS n FROM (SELECT {_status(R)} AS status FROM orders) GROUP BY ALL",
    "udtf_attack_paths": "WITH RECURSIVE" + INSTANCES.removeprefix("WITH") + ", e(src, label, dst) AS (SELECT conv_id * 16 + s, label, conv_id * 16 + d FROM each, (VALUES " + ", ".join(f"({s}, '{label}', {d})" for s, label, d in _EDGE_ROWS if label != "published_to") + """) AS t(s, label, d) WHERE flagged),
walk(target, vid, hops, path, crossed) AS (SELECT conv_id * 16 + t, conv_id * 16 + t, 0, (conv_id * 16 + t)::VARCHAR, [conv_id * 16 + t] FROM each, (VALUES (9), (10)) AS t(t) WHERE flagged
  UNION ALL SELECT w.target, e.src, w.hops + 1, e.src || ' -' || e.label || '-> ' || w.path, list_append(w.crossed, e.src) FROM walk w JOIN e ON e.dst = w.vid WHERE w.hops < 10 AND NOT list_contains(w.crossed, e.src))
SELECT target, vid AS fact, hops::INTEGER AS hops, path FROM walk WHERE vid % 16 IN (3, 4, 6)""",
    "buildlog_edges": """WITH l AS (SELECT DISTINCT l_orderkey AS ok, l_partkey AS pk, l_returnflag AS f FROM lineitem JOIN orders ON o_orderkey = l_orderkey),
o AS (SELECT o_orderkey AS ok, o_custkey || '/' || strftime(o_orderdate, '%Y-%m') AS env FROM orders)
SELECT 'feeds' AS label, 'artifact' AS src_type, 'step' AS dst_type, count(*) AS n FROM l WHERE f = 'N'
UNION ALL SELECT 'tools', 'artifact', 'step', count(*) FROM l WHERE f = 'R'
UNION ALL SELECT 'present_in', 'artifact', 'env', count(*) FROM (SELECT DISTINCT pk, env FROM l JOIN o USING (ok) WHERE f = 'A')
UNION ALL SELECT 'runs_step', 'env', 'step', count(*) FROM o
UNION ALL SELECT 'hosts_env', 'host', 'env', count(DISTINCT env) FROM o
UNION ALL SELECT 'produces', 'step', 'artifact', count(*) FROM o""",
    "udtf_example": "SELECT * FROM (VALUES " + ", ".join(f"({s}::BIGINT, '{label}', {d}::BIGINT)" for s, label, d in _EDGE_ROWS) + ") AS t(src, label, dst)",
    "sql_surface": f"{_with(_edges(), _levels(BOTH), RAW)} SELECT label, {_status('src')} AS status, count(*) AS n FROM raw GROUP BY ALL",
}
