"""SQL of the same results, written from the definitions, for another engine to run on the same tables.

Each string is a chain of common table expressions: a graph as e(u, v, w) and n(id), derived tables, and
a last SELECT. Iterative methods are unrolled over a fixed number of rounds.
"""

from __future__ import annotations

_P = 2147483647

GRAPHS: dict[str, str] = {
    "basket": """d AS (SELECT DISTINCT l_orderkey k, l_partkey i FROM lineitem),
e AS (SELECT a.i u, b.i v, count(*) w FROM d a JOIN d b USING (k) WHERE a.i < b.i GROUP BY 1, 2), n AS (SELECT DISTINCT i id FROM d)""",
    "cosupply": """d AS (SELECT DISTINCT l_orderkey k, l_suppkey i FROM lineitem),
e AS (SELECT a.i u, b.i v, count(*) w FROM d a JOIN d b USING (k) WHERE a.i < b.i GROUP BY 1, 2), n AS (SELECT DISTINCT i id FROM d)""",
    "trade": """e AS (SELECT o_custkey u, l_suppkey + 144115188075855872 v, count(*) w FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1, 2),
n AS (SELECT u id FROM e UNION SELECT v FROM e)""",
    "supply": """e AS (SELECT DISTINCT l_partkey u, l_suppkey + 144115188075855872 v, 1 w FROM lineitem), n AS (SELECT u id FROM e UNION SELECT v FROM e)""",
    "geo": """e AS (SELECT c_custkey u, c_nationkey::BIGINT + 72057594037927936 v, 1 w FROM customer
  UNION ALL SELECT n_nationkey::BIGINT + 72057594037927936, s_suppkey + 144115188075855872, 1 FROM supplier JOIN nation ON s_nationkey = n_nationkey
  UNION ALL SELECT n_nationkey::BIGINT + 72057594037927936, n_regionkey::BIGINT + 216172782113783808, 1 FROM nation),
n AS (SELECT u id FROM e UNION SELECT v FROM e),
t AS (SELECT c_custkey id, c_nationkey::BIGINT + 72057594037927936 comm FROM customer UNION ALL SELECT s_suppkey + 144115188075855872, s_nationkey::BIGINT + 72057594037927936 FROM supplier
  UNION ALL SELECT n_nationkey::BIGINT + 72057594037927936, n_nationkey::BIGINT + 72057594037927936 FROM nation UNION ALL SELECT r_regionkey::BIGINT + 216172782113783808, r_regionkey::BIGINT + 216172782113783808 FROM region)""",
    "planted": f"""z AS (SELECT count(*) c, greatest(5, count(*) // 50) b, count(*) // greatest(5, count(*) // 50) k FROM part),
h AS (SELECT l_partkey a, (l_orderkey * 7919 + l_linenumber::BIGINT * 104729 + l_suppkey * 31) % 1000003 h FROM lineitem),
q AS (SELECT a, CASE WHEN ((h * 48271 + 11) % {_P}) % 10 < 5 THEN ((h * 69621 + a * 7 + 13) % {_P}) % c ELSE a % b + b * (((h * 16807 + a * 3 + 5) % {_P}) % k) END o FROM h, z),
e AS (SELECT least(a, o) u, greatest(a, o) v, count(*) w FROM q WHERE a <> o GROUP BY 1, 2), n AS (SELECT u id FROM e UNION SELECT v FROM e),
t AS (SELECT p_partkey id, p_partkey % b comm FROM part, z WHERE p_partkey IN (SELECT id FROM n))""",
    "neardup": """ws AS (SELECT doc_id i, list_filter(string_split_regex(lower(trim(text)), '\\s+'), lambda x: x <> '') ws FROM documents),
sh AS (SELECT DISTINCT i, md5(array_to_string(ws[j : j + 4], ' ')) s FROM (SELECT i, ws, unnest(range(1, len(ws) - 3)) j FROM ws WHERE len(ws) >= 5)),
ra AS (SELECT s FROM sh GROUP BY s HAVING count(*) BETWEEN 2 AND 50), kp AS (SELECT i, s FROM sh SEMI JOIN ra USING (s)),
e AS (SELECT a.i u, b.i v, count(*) w FROM kp a JOIN kp b USING (s) WHERE a.i < b.i GROUP BY 1, 2), n AS (SELECT u id FROM e UNION SELECT v FROM e)""",
    "pagelinks": """li AS (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) href FROM pages),
hi AS (SELECT href, row_number() OVER (ORDER BY href) - 1 + 72057594037927936 hid FROM (SELECT DISTINCT href FROM li)),
e AS (SELECT page_id u, hid v, count(*) w FROM li JOIN hi USING (href) GROUP BY 1, 2), n AS (SELECT u id FROM e UNION SELECT v FROM e)""",
    "pagepages": """li AS (SELECT DISTINCT page_id i, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) k FROM pages),
e AS (SELECT a.i u, b.i v, count(*) w FROM li a JOIN li b USING (k) WHERE a.i < b.i GROUP BY 1, 2), n AS (SELECT DISTINCT i id FROM li),
t AS (SELECT i id, min(i) OVER (PARTITION BY s) comm FROM (SELECT i, string_agg(k, ' ' ORDER BY k) s FROM li GROUP BY i))""",
    "turns": """e AS (SELECT a.conv_id * 16777216 + a.turn u, a.conv_id * 16777216 + a.turn + 1 v, 1 w FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1),
n AS (SELECT conv_id * 16777216 + turn id FROM conversations), t AS (SELECT conv_id * 16777216 + turn id, conv_id comm FROM conversations)""",
    "coactive": """d AS (SELECT DISTINCT event_type k, date_trunc('hour', ts) h, user_id i FROM events),
e AS (SELECT a.i u, b.i v, count(*) w FROM d a JOIN d b USING (k, h) WHERE a.i < b.i GROUP BY 1, 2), n AS (SELECT DISTINCT i id FROM d)""",
    "useritem": """e AS (SELECT user_id u, list_position(['click', 'error', 'purchase', 'signup', 'view'], event_type) * 100 + (props ->> '$.k')::BIGINT + 72057594037927936 v, count(*) w FROM events GROUP BY 1, 2),
n AS (SELECT u id FROM e UNION SELECT v FROM e)""",
}

ARCS = "arcs AS (SELECT u src, v dst, w FROM e WHERE u <> v UNION ALL SELECT v, u, w FROM e WHERE u <> v)"
VOL = "vol AS (SELECT id, coalesce(sum(w), 0)::BIGINT vol FROM n LEFT JOIN (SELECT u i, w FROM e UNION ALL SELECT v, w FROM e) ON i = id GROUP BY id), tot AS (SELECT sum(w)::BIGINT tw FROM e)"
ONE = "s0 AS (SELECT id, id comm FROM n)"


def slot(column: str, round_no: int, slots: int, seed: int = 0) -> str:
    mixed = f"(({column} % {_P} * 48271 + {(seed * 69621 + round_no * 16807) % _P}) % {_P})"
    return f"({mixed} * {mixed} % {_P}) % {slots}"


def lp_round(before: str, after: str, ties: str = "keep_min", weighted: bool = True, where: str = "true") -> str:
    """One sub-round of label propagation as CTEs."""
    order = {"keep_min": "(v.comm = o.comm) DESC, v.comm", "min": "v.comm", "hash": f"(v.comm % {_P} * 48271) % {_P}, v.comm"}[ties]
    return f"""{after}_v AS (SELECT a.src id, l.comm, {"sum(a.w)" if weighted else "count(*)"} w FROM arcs a JOIN {before} l ON l.id = a.dst GROUP BY 1, 2),
{after}_k AS (SELECT v.id, v.comm, row_number() OVER (PARTITION BY v.id ORDER BY v.w DESC, {order}) k FROM {after}_v v JOIN {before} o ON o.id = v.id),
{after} AS (SELECT o.id, CASE WHEN {where} THEN coalesce(x.comm, o.comm) ELSE o.comm END comm FROM {before} o LEFT JOIN {after}_k x ON x.id = o.id AND x.k = 1)"""


def gains(state: str, p: int = 1, q: int = 1, name: str = "sc", vol: str = "vol", arcs: str = "arcs") -> str:
    """Scores of all moves to communities around."""
    return f"""{name}_w AS (SELECT a.src id, s.comm, sum(a.w) w FROM {arcs} a JOIN {state} s ON s.id = a.dst GROUP BY 1, 2),
{name}_c AS (SELECT comm, sum(vol) vol, count(*) size FROM {state} JOIN {vol} USING (id) GROUP BY 1),
{name} AS (SELECT x.id, s.comm from_comm, x.comm to_comm, (2::HUGEINT * {q} * tw * (x.w - coalesce(o.w, 0)) + {p}::HUGEINT * y.vol * (f.vol - y.vol - t.vol)) score, f.size = 1 sf, t.size = 1 st
  FROM {name}_w x JOIN {state} s ON s.id = x.id JOIN {vol} y ON y.id = x.id LEFT JOIN {name}_w o ON o.id = x.id AND o.comm = s.comm JOIN {name}_c f ON f.comm = s.comm JOIN {name}_c t ON t.comm = x.comm, tot WHERE x.comm <> s.comm)"""


def move_round(before: str, after: str, vol: str = "vol", arcs: str = "arcs", where: str = "true") -> str:
    return f"""{gains(before, name=after + "_s", vol=vol, arcs=arcs)},
{after}_b AS (SELECT id, to_comm, row_number() OVER (PARTITION BY id ORDER BY score DESC, to_comm) k FROM {after}_s WHERE score > 0 AND NOT (sf AND st AND to_comm > from_comm) AND {where}),
{after} AS (SELECT s.id, coalesce(b.to_comm, s.comm) comm FROM {before} s LEFT JOIN {after}_b b ON b.id = s.id AND b.k = 1)"""


def named(state: str, name: str) -> str:
    return f"{name} AS (SELECT id, min(id) OVER (PARTITION BY comm) comm FROM {state})"


def contracted(edges: str, state: str, name: str) -> str:
    return f"{name} AS (SELECT least(a.comm, b.comm) u, greatest(a.comm, b.comm) v, sum(w)::BIGINT w FROM {edges} x JOIN {state} a ON a.id = x.u JOIN {state} b ON b.id = x.v GROUP BY 1, 2)"


def query(graph: str, *parts: str, select: str) -> str:
    return "WITH " + ",\n".join([GRAPHS[graph], *parts]) + "\n" + select
