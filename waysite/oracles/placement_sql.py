"""DuckDB statements that answer the placement queries from the raw tables, built from the same parameters."""

from __future__ import annotations

import math

PRIME = 2_147_483_647


def lattice(n: int) -> str:
    side = math.isqrt(max(n - 1, 0)) + 1
    return f"""nodes AS (SELECT CAST(i AS BIGINT) AS node_id, i % {side} AS x, i // {side} AS y FROM range({n}) r(i)),
roads AS (SELECT node_id AS src, node_id + 1 AS dst FROM nodes WHERE x < {side - 1} AND node_id + 1 < {n}
          UNION ALL SELECT node_id, node_id + {side} FROM nodes WHERE node_id + {side} < {n}),
edges AS (SELECT src, dst, CAST(100 + (31 * src + 17 * dst) % 50 AS BIGINT) AS metres FROM (SELECT src, dst FROM roads UNION ALL SELECT dst, src FROM roads) b)"""


def lattice_of(table: str) -> str:
    """The lattice of as many nodes as a table has rows."""
    n = f"(SELECT count(*) FROM {table})"
    side = f"(SELECT CAST(ceil(sqrt(count(*))) AS BIGINT) FROM {table})"
    return f"""nodes AS MATERIALIZED (SELECT CAST(i AS BIGINT) AS node_id, i % {side} AS x, i // {side} AS y FROM range({n}) r(i)),
roads AS (SELECT node_id AS src, node_id + 1 AS dst FROM nodes WHERE x < {side} - 1 AND node_id + 1 < {n}
          UNION ALL SELECT node_id, node_id + {side} FROM nodes WHERE node_id + {side} < {n}),
edges AS MATERIALIZED (SELECT src, dst, CAST(100 + (31 * src + 17 * dst) % 50 AS BIGINT) AS metres FROM (SELECT src, dst FROM roads UNION ALL SELECT dst, src FROM roads) b)"""


VISITED, HOMES = "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS id FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL", "SELECT c_nationkey AS id FROM customer WHERE c_nationkey IS NOT NULL"


def lattice_over(ids: str) -> str:
    """The lattice over the different ids of a given table."""
    return "given AS MATERIALIZED (SELECT DISTINCT id FROM (" + ids + ") g),\n" + lattice_of("given").replace("(SELECT CAST(i AS BIGINT) AS node_id, i %", "(SELECT CAST(id AS BIGINT) AS node_id, id %", 1).replace(", i // ", ", id // ", 1).replace("FROM range((SELECT count(*) FROM given)) r(i))", "FROM given)", 1)


DIST = """reach(src, dst, metres) USING KEY (src, dst) AS (
  SELECT node_id, node_id, CAST(0 AS BIGINT) FROM nodes
  UNION
  SELECT src, dst, metres FROM (
    SELECT r.src AS src, e.dst AS dst, min(r.metres + e.metres) AS metres FROM reach r JOIN edges e ON r.dst = e.src GROUP BY r.src, e.dst) step
  WHERE NOT EXISTS (SELECT 1 FROM recurring.reach k WHERE k.src = step.src AND k.dst = step.dst AND k.metres <= step.metres)
),
dist AS MATERIALIZED (SELECT src, dst, metres FROM reach)"""

TRIPS = """round_trips AS MATERIALIZED (SELECT a.src AS a, a.dst AS b, a.metres + b.metres AS metres FROM dist a JOIN dist b ON a.src = b.dst AND a.dst = b.src)"""

VISITS = """visits AS (SELECT user_id, ts, event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS node_id FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL)"""

DAY_POINTS = f"""{VISITS},
points AS MATERIALIZED (SELECT path_id, CAST(row_number() OVER (PARTITION BY path_id ORDER BY ts, event_id) - 1 AS INTEGER) AS seq, node_id, ts
  FROM (SELECT *, user_id * 100 + date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS path_id FROM visits) v)"""

NATION_POINTS = """points AS MATERIALIZED (SELECT l_orderkey AS path_id, CAST(row_number() OVER (PARTITION BY l_orderkey ORDER BY l_shipdate, l_linenumber, l_suppkey, l_partkey) - 1 AS INTEGER) AS seq,
  CAST(s_nationkey AS BIGINT) AS node_id, l_shipdate AS ts FROM lineitem JOIN supplier ON l_suppkey = s_suppkey)"""


SUPPLIER_POINTS = """points AS MATERIALIZED (SELECT l_orderkey AS path_id, CAST(row_number() OVER (PARTITION BY l_orderkey ORDER BY l_shipdate, l_linenumber, l_suppkey, l_partkey) - 1 AS INTEGER) AS seq,
  CAST(l_suppkey - 1 AS BIGINT) AS node_id, l_shipdate AS ts FROM lineitem)"""


def filled(side: int, source: str = "points") -> str:
    """Nodes between visits, along x and then along y."""
    return f"""lagged AS (SELECT *, lag(node_id) OVER (PARTITION BY path_id ORDER BY seq) AS last FROM {source}),
walked AS (SELECT path_id, seq, ts, CASE WHEN last IS NULL OR last = node_id THEN [node_id] ELSE list_concat(
    list_transform(CASE WHEN node_id % {side} > last % {side} THEN range(last % {side} + 1, node_id % {side} + 1) WHEN node_id % {side} < last % {side} THEN range(last % {side} - 1, node_id % {side} - 1, -1) ELSE [] END, lambda v: (last // {side}) * {side} + v),
    list_transform(CASE WHEN node_id // {side} > last // {side} THEN range(last // {side} + 1, node_id // {side} + 1) WHEN node_id // {side} < last // {side} THEN range(last // {side} - 1, node_id // {side} - 1, -1) ELSE [] END, lambda v: v * {side} + node_id % {side})) END AS steps FROM lagged),
filled_points AS MATERIALIZED (SELECT path_id, CAST(row_number() OVER (PARTITION BY path_id ORDER BY seq, sub) - 1 AS INTEGER) AS seq, CAST(node AS BIGINT) AS node_id, ts
  FROM (SELECT path_id, seq, ts, unnest(steps) AS node, unnest(range(len(steps))) AS sub FROM walked) u)"""


def detour(pair: str = "any", points: str = "points") -> str:
    if pair == "same":
        return f"""pn AS (SELECT DISTINCT path_id, node_id FROM {points}),
detour AS MATERIALIZED (SELECT p.path_id, t.dst AS site_id, min(t.metres + b.metres) AS metres FROM pn p JOIN dist t ON t.src = p.node_id JOIN dist b ON b.src = t.dst AND b.dst = p.node_id GROUP BY ALL)"""
    order = " AND b.seq >= a.seq" if pair == "forward" else ""
    return f"""pairs AS MATERIALIZED (SELECT DISTINCT a.path_id, a.node_id AS v, b.node_id AS w FROM {points} a JOIN {points} b ON a.path_id = b.path_id{order}),
extra AS MATERIALIZED (SELECT q.v, q.w, t.dst AS s, t.metres + b.metres - g.metres AS metres
  FROM (SELECT DISTINCT v, w FROM pairs) q JOIN dist g ON g.src = q.v AND g.dst = q.w JOIN dist t ON t.src = q.v JOIN dist b ON b.src = t.dst AND b.dst = q.w),
detour AS MATERIALIZED (SELECT path_id, s AS site_id, min(metres) AS metres FROM pairs JOIN extra USING (v, w) GROUP BY ALL)"""


def cover(tau: float, value: str = "1.0", source: str = "detour") -> str:
    return f"cover AS MATERIALIZED (SELECT * FROM (SELECT path_id, site_id, metres, CAST(round(({value}) * 1000000) AS BIGINT) AS score FROM {source} WHERE metres <= {tau}) c WHERE score > 0)"


PREFERENCES = {
    "binary": "1.0",
    "linear": "1 - metres / {tau}.0::DOUBLE",
    "convex": "pow(1 - metres / {tau}.0::DOUBLE, 2)",
    "exponential": "exp(-3 * metres / {tau}.0::DOUBLE)",
}


def chain(*parts: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(p for p in parts if p) + "\n"


def greedy(k: int, existing: tuple[int, ...] = (), n: int = 100, taken_rule: str = "") -> str:
    """k picks unrolled: each step's best scores, gains and pick are one relation each."""
    held = f"SELECT path_id, max(score) AS u FROM cover WHERE site_id IN ({', '.join(map(str, existing))}) GROUP BY path_id" if existing else "SELECT CAST(NULL AS BIGINT) AS path_id, CAST(NULL AS BIGINT) AS u WHERE false"
    parts = ["weights AS MATERIALIZED (SELECT site_id, sum(score) AS weight FROM cover GROUP BY site_id)", f"u0 AS MATERIALIZED ({held})"]
    picks: list[str] = []
    for i in range(1, k + 1):
        out = " UNION ALL ".join(f"SELECT site_id FROM pick{j}" for j in range(1, i)) or "SELECT CAST(NULL AS BIGINT) WHERE false"
        gone = f"{out} UNION ALL SELECT unnest([{', '.join(map(str, existing))}])" if existing else out
        parts.append(f"""pick{i} AS MATERIALIZED (SELECT {i} AS step, s.site_id, CAST(coalesce(g.gain, 0) AS BIGINT) AS gain FROM (SELECT CAST(i AS BIGINT) AS site_id FROM range({n}) r(i)) s
  LEFT JOIN (SELECT c.site_id, sum(greatest(c.score - coalesce(u.u, 0), 0)) AS gain FROM cover c LEFT JOIN u{i - 1} u USING (path_id) GROUP BY c.site_id) g USING (site_id)
  LEFT JOIN weights w USING (site_id) WHERE s.site_id NOT IN (SELECT x.site_id FROM ({gone}) x(site_id) WHERE x.site_id IS NOT NULL)
  ORDER BY coalesce(g.gain, 0) DESC, coalesce(w.weight, 0) DESC, s.site_id DESC LIMIT 1)""")
        parts.append(f"u{i} AS MATERIALIZED (SELECT path_id, max(u) AS u FROM (SELECT * FROM u{i - 1} UNION ALL SELECT path_id, score FROM cover WHERE site_id = (SELECT site_id FROM pick{i})) z GROUP BY path_id)")
        picks.append(f"SELECT * FROM pick{i}")
    parts.append(f"picks AS ({' UNION ALL '.join(picks)})")
    return ",\n".join(parts)


PLACED = """SELECT step, site_id, gain, CAST((SELECT coalesce(sum(u), 0) FROM u0) + sum(gain) OVER (ORDER BY step) AS BIGINT) AS utility,
  round(((SELECT coalesce(sum(u), 0) FROM u0) + sum(gain) OVER (ORDER BY step)) / 1000000 / (SELECT count(DISTINCT path_id) FROM points) * 100, 6) AS utility_pct FROM picks"""


def day_cover(tau: float = 400, preference: str = "binary", pair: str = "any") -> tuple[str, ...]:
    return (lattice(100), DIST, DAY_POINTS, detour(pair), cover(tau, PREFERENCES[preference].format(tau=tau)))


def fm_words(f: int, source: str = "cover", key: str = "site_id", item: str = "path_id") -> str:
    pairs = ", ".join(f"({c}, {pow(16807, 3 * c + 5, PRIME)}, {pow(16807, 7 * c + 11, PRIME)})" for c in range(f))
    return f"""family(copy, a, b) AS (VALUES {pairs}),
hashes AS (SELECT {key}, copy, (CAST(a AS BIGINT) * ({item} % {PRIME}) + b) % {PRIME} AS h FROM {source}, family),
words AS (SELECT {key}, copy, bit_or(CASE WHEN h = 0 THEN CAST(1 AS BIGINT) << 31 ELSE CAST(1 AS BIGINT) << CAST(bit_count((h & -h) - 1) AS BIGINT) END) AS word FROM hashes GROUP BY ALL)"""


def clusters(radius: float) -> str:
    """Greedy dominating clusters as one recursion that carries the nodes already taken."""
    return f"""dom AS MATERIALIZED (SELECT a AS node, list(b) AS members FROM round_trips WHERE metres <= {2 * radius} GROUP BY a),
build(i, centre, taken, fresh) AS (
  SELECT 0, CAST(-1 AS BIGINT), CAST([] AS BIGINT[]), CAST([] AS BIGINT[])
  UNION ALL
  (SELECT b.i + 1, d.node, list_concat(b.taken, list_filter(d.members, lambda m: NOT list_contains(b.taken, m))), list_filter(d.members, lambda m: NOT list_contains(b.taken, m))
   FROM build b, dom d WHERE NOT list_contains(b.taken, d.node)
   ORDER BY len(list_filter(d.members, lambda m: NOT list_contains(b.taken, m))) DESC, d.node LIMIT 1)
),
member AS MATERIALIZED (SELECT b.centre AS cluster_id, f.node_id, t.metres FROM build b, unnest(b.fresh) f(node_id) JOIN round_trips t ON t.a = b.centre AND t.b = f.node_id)"""
