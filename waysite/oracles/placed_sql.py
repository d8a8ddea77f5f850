"""DuckDB statements of placements with constraints, of index levels and of the workloads: relations are named, so that
one statement can hold many of them."""

from __future__ import annotations

from waysite.oracles.placement_sql import DAY_POINTS, DIST, PREFERENCES, PRIME, TRIPS, chain, detour, filled, lattice

#: Round trips between two nodes of the 100-node lattice: the thresholds of its index.
LIMITS_100 = (210, 4034)
ALL_NODES = "SELECT node_id AS site_id FROM nodes"


def cover(name: str, tau: float, preference: str = "binary", source: str = "detour", where: str = "true") -> str:
    value = PREFERENCES[preference].format(tau=tau)
    return f"{name} AS MATERIALIZED (SELECT * FROM (SELECT path_id, site_id, metres, CAST(round(({value}) * 1000000) AS BIGINT) AS score FROM {source} WHERE metres <= {tau} AND ({where})) c WHERE score > 0)"


def hash_normal(column: str = "node_id") -> str:
    terms = " + ".join(f"({pow(48271, c + 1, PRIME)}::BIGINT * ({column} + 1) + {pow(16807, c + 1, PRIME)}) % {PRIME}" for c in range(12))
    return f"(CAST({terms} AS DOUBLE) / {PRIME}.0::DOUBLE - 6.0::DOUBLE)"


def attributed(sigma: float | None = None, mean: str | None = None, source: str = "nodes") -> str:
    """Candidate sites with the costs and capacities that the fixtures give them."""
    cost = "" if sigma is None else f", round(greatest(0.1::DOUBLE, 1 + {sigma}::DOUBLE * {hash_normal()}), 4) AS cost"
    room = "" if mean is None else f", CAST(greatest(0, round(({mean}) * (1 + 0.1::DOUBLE * {hash_normal()}))) AS BIGINT) AS room"
    return f"SELECT node_id AS site_id{cost}{room} FROM {source}"


def steps(name: str, cover: str, k: int, candidates: str = ALL_NODES, existing: tuple[int, ...] = (), capacity: bool = False, forced: str | None = None) -> str:
    """Relations {name}_pick1 ... of (step, site_id, gain), of no row once nothing can be picked, and {name} of all.
    capacity: a site serves its largest gains only, up to its room. forced:
    the sites of another relation are taken, one a step."""
    held = f"SELECT path_id, max(score) AS u FROM {cover} WHERE site_id IN ({', '.join(map(str, existing))}) GROUP BY path_id" if existing else "SELECT CAST(NULL AS BIGINT) AS path_id, CAST(NULL AS BIGINT) AS u WHERE false"
    out = [f"{name}_cand AS MATERIALIZED ({candidates})", f"{name}_w AS MATERIALIZED (SELECT site_id, sum(score) AS weight FROM {cover} GROUP BY site_id)", f"{name}_u0 AS MATERIALIZED ({held})"]
    room = f" JOIN {name}_cand d USING (site_id)" if capacity else ""
    for i in range(1, k + 1):
        taken = " UNION ALL ".join(["SELECT CAST(-1 AS BIGINT) AS site_id", *(f"SELECT site_id FROM {name}_pick{j}" for j in range(1, i)), *(f"SELECT {e}" for e in existing)])
        limited = f"SELECT c.path_id, c.site_id, c.score, c.score - coalesce(u.u, 0) AS gain{', row_number() OVER (PARTITION BY c.site_id ORDER BY c.score - coalesce(u.u, 0) DESC, c.path_id) AS place, d.room' if capacity else ''} FROM {cover} c LEFT JOIN {name}_u{i - 1} u USING (path_id){room} WHERE c.score > coalesce(u.u, 0)"
        rows = f"(SELECT * FROM ({limited}) q{' WHERE room IS NULL OR place <= room' if capacity else ''})"
        chosen = f" AND s.site_id = (SELECT site_id FROM {forced}_pick{i})" if forced else ""
        out.append(f"""{name}_pick{i} AS MATERIALIZED (SELECT {i} AS step, s.site_id, CAST(coalesce(g.gain, 0) AS BIGINT) AS gain FROM {name}_cand s
  LEFT JOIN (SELECT site_id, sum(gain) AS gain FROM {rows} r GROUP BY site_id) g USING (site_id) LEFT JOIN {name}_w w USING (site_id)
  WHERE s.site_id NOT IN (SELECT site_id FROM ({taken}) t){chosen} ORDER BY coalesce(g.gain, 0) DESC, coalesce(w.weight, 0) DESC, s.site_id DESC LIMIT 1)""")
        out.append(f"{name}_u{i} AS MATERIALIZED (SELECT path_id, max(u) AS u FROM (SELECT * FROM {name}_u{i - 1} UNION ALL SELECT path_id, score FROM {rows} r WHERE site_id = (SELECT site_id FROM {name}_pick{i})) z GROUP BY path_id)")
    picks = " UNION ALL ".join(f"SELECT * FROM {name}_pick{i}" for i in range(1, k + 1))
    out.append(f"{name} AS ({picks})")
    return ",\n".join(out)


def budget_steps(name: str, cover: str, candidates: str, budget: float, safeguard: bool = True) -> str:
    """{name}(step, site_id, gain, cost): gain for cost among what is affordable, as one recursion that carries the open
    sites and what is left; in the end the best single site where it alone is better."""
    better = f"(SELECT gain FROM {name}_one) > (SELECT sum(gain) FROM {name}_all)" if safeguard else "false"
    return f"""{name}_cand AS MATERIALIZED ({candidates}),
{name}_w AS MATERIALIZED (SELECT s.site_id, s.cost, coalesce(sum(c.score), 0) AS weight FROM {name}_cand s LEFT JOIN {cover} c USING (site_id) GROUP BY ALL),
{name}_u0 AS (SELECT CAST(NULL AS BIGINT) AS path_id, CAST(NULL AS BIGINT) AS u WHERE false),
{name}_run(step, site_id, gain, cost, chosen, rest) AS (
  SELECT 0, CAST(-1 AS BIGINT), CAST(0 AS BIGINT), 0.0::DOUBLE, CAST([] AS BIGINT[]), {budget}::DOUBLE
  UNION ALL
  (SELECT r.step + 1, g.site_id, CAST(g.gain AS BIGINT), g.cost, list_append(r.chosen, g.site_id), round(r.rest - g.cost, 9)
   FROM {name}_run r, (SELECT w.site_id, w.cost, w.weight, coalesce(sum(greatest(c.score - coalesce(u.u, 0), 0)), 0) AS gain FROM {name}_w w LEFT JOIN {cover} c USING (site_id)
     LEFT JOIN (SELECT o.path_id, max(o.score) AS u FROM {cover} o, {name}_run t WHERE list_contains(t.chosen, o.site_id) GROUP BY o.path_id) u ON u.path_id = c.path_id GROUP BY ALL) g
   WHERE NOT list_contains(r.chosen, g.site_id) AND g.cost <= r.rest ORDER BY g.gain / g.cost DESC, g.gain DESC, g.weight DESC, g.site_id DESC LIMIT 1)
),
{name}_all AS MATERIALIZED (SELECT step, site_id, gain, cost FROM {name}_run WHERE step > 0),
{name}_one AS MATERIALIZED (SELECT 1 AS step, site_id, CAST(weight AS BIGINT) AS gain, cost FROM {name}_w WHERE cost <= {budget} ORDER BY weight DESC, site_id DESC LIMIT 1),
{name} AS (SELECT * FROM {name}_one WHERE {better} UNION ALL SELECT * FROM {name}_all WHERE NOT ({better}))"""


def placed(name: str, points: str = "points", picks: str | None = None) -> str:
    """The rows of a placement: utility with the existing sites'."""
    base = f"(SELECT coalesce(sum(u), 0) FROM {name}_u0)"
    return f"""SELECT step, site_id, gain, CAST({base} + sum(gain) OVER (ORDER BY step) AS BIGINT) AS utility,
  round(({base} + sum(gain) OVER (ORDER BY step)) / 1000000 / (SELECT count(DISTINCT path_id) FROM {points}) * 100, 6) AS utility_pct FROM {picks or name}"""


def valued(sites: str, cover: str, points: str) -> str:
    """Percent of the paths' utility under the sites of a relation, on a cover."""
    return f"(SELECT round(coalesce(sum(u), 0) / 1000000 / (SELECT count(DISTINCT path_id) FROM {points}) * 100, 6) FROM (SELECT path_id, max(score) AS u FROM {cover} WHERE site_id IN (SELECT site_id FROM {sites}) GROUP BY path_id) v)"


def sketch_steps(name: str, cover: str, k: int, copies: int) -> str:
    """The sketch greedy: relations as steps() has them, without gains; the sites only."""
    pairs = ", ".join(f"({c}, {pow(16807, 3 * c + 5, PRIME)}, {pow(16807, 7 * c + 11, PRIME)})" for c in range(copies))
    low = "bit_count((~word & (word + 1)) - 1)"
    out = [f"""{name}_words AS MATERIALIZED (SELECT site_id, copy, bit_or(CASE WHEN h = 0 THEN CAST(1 AS BIGINT) << 31 ELSE CAST(1 AS BIGINT) << CAST(bit_count((h & -h) - 1) AS BIGINT) END) AS word
  FROM (SELECT site_id, copy, (CAST(a AS BIGINT) * (path_id % {PRIME}) + b) % {PRIME} AS h FROM {cover}, (VALUES {pairs}) f(copy, a, b)) x GROUP BY ALL)""",
        f"{name}_own AS MATERIALIZED (SELECT site_id, pow(2.0, sum({low}) / count(*)) / 0.77351 AS own FROM {name}_words GROUP BY site_id)",
        f"{name}_b0 AS MATERIALIZED (SELECT copy, CAST(0 AS BIGINT) AS word FROM range({copies}) r(copy))"]
    for i in range(1, k + 1):
        taken = " UNION ALL ".join(["SELECT CAST(-1 AS BIGINT) AS site_id", *(f"SELECT site_id FROM {name}_pick{j}" for j in range(1, i))])
        now = f"(SELECT CASE WHEN bit_or(word) = 0 THEN 0.0 ELSE pow(2.0, sum({low}) / count(*)) / 0.77351 END FROM {name}_b{i - 1})"
        out.append(f"""{name}_pick{i} AS MATERIALIZED (SELECT {i} AS step, site_id FROM (SELECT site_id, pow(2.0, sum({low}) / count(*)) / 0.77351 - {now} AS gain
  FROM (SELECT w.site_id, w.word | b.word AS word FROM {name}_words w JOIN {name}_b{i - 1} b USING (copy)) j GROUP BY site_id) g JOIN {name}_own USING (site_id)
  WHERE site_id NOT IN (SELECT site_id FROM ({taken}) t) ORDER BY gain DESC, own DESC, site_id DESC LIMIT 1)""")
        out.append(f"{name}_b{i} AS MATERIALIZED (SELECT copy, b.word | w.word AS word FROM {name}_b{i - 1} b JOIN {name}_words w USING (copy) WHERE w.site_id = (SELECT site_id FROM {name}_pick{i}))")
    out.append(f"{name} AS ({' UNION ALL '.join(f'SELECT * FROM {name}_pick{i}' for i in range(1, k + 1))})")
    return ",\n".join(out)


def level_radii(limits: tuple[float, float] = LIMITS_100, eps: float = 0.75) -> list[float]:
    out, low = [], float(limits[0])
    while low <= limits[1]:
        out.append(low / 4)
        low *= 1 + eps
    return out


def level_of(tau: float, limits: tuple[float, float] = LIMITS_100, eps: float = 0.75) -> int:
    return max(p for p, r in enumerate(level_radii(limits, eps)) if 4 * r <= tau)


def members(level: int, radius: float) -> str:
    """member{level}(cluster_id, node_id, metres): greedy dominating clusters as one recursion."""
    return f"""dom{level} AS MATERIALIZED (SELECT a AS node, list(b) AS members FROM round_trips WHERE metres <= {2 * radius} GROUP BY a),
build{level}(i, centre, taken, fresh) AS (
  SELECT 0, CAST(-1 AS BIGINT), CAST([] AS BIGINT[]), CAST([] AS BIGINT[])
  UNION ALL
  (SELECT b.i + 1, d.node, list_concat(b.taken, list_filter(d.members, lambda m: NOT list_contains(b.taken, m))), list_filter(d.members, lambda m: NOT list_contains(b.taken, m))
   FROM build{level} b, dom{level} d WHERE NOT list_contains(b.taken, d.node)
   ORDER BY len(list_filter(d.members, lambda m: NOT list_contains(b.taken, m))) DESC, d.node LIMIT 1)
),
member{level} AS MATERIALIZED (SELECT b.centre AS cluster_id, f.node_id, t.metres FROM build{level} b, unnest(b.fresh) f(node_id) JOIN round_trips t ON t.a = b.centre AND t.b = f.node_id)"""


def level_relations(level: int, radius: float, eps: float = 0.75, points: str = "points", source: str = "detour", site: str = "true") -> str:
    """member, link, own (path lists) and rep relations of one level; site: which nodes are sites."""
    return f"""{members(level, radius)},
centre{level} AS MATERIALIZED (SELECT DISTINCT cluster_id FROM member{level}),
link{level} AS MATERIALIZED (SELECT a AS cluster_id, b AS nbr_id, metres FROM round_trips JOIN centre{level} x ON x.cluster_id = a JOIN centre{level} y ON y.cluster_id = b WHERE a <> b AND metres <= {4 * radius * (1 + eps)}),
own{level} AS MATERIALIZED (SELECT DISTINCT m.cluster_id, p.path_id, d.metres FROM {points} p JOIN member{level} m USING (node_id) JOIN {source} d ON d.path_id = p.path_id AND d.site_id = m.cluster_id),
rep{level} AS MATERIALIZED (SELECT cluster_id, arg_min(node_id, struct_pack(metres, node_id)) AS rep, min(metres) AS rep_metres FROM member{level} WHERE {site} GROUP BY cluster_id)"""


def estimated(level: int, existing: tuple[int, ...] = ()) -> str:
    """est{level}(path_id, site_id, metres): over centres to representatives, and to existing sites at their own places."""
    more = f" UNION SELECT cluster_id, node_id, metres FROM member{level} WHERE node_id IN ({', '.join(map(str, existing))})" if existing else ""
    return f"""target{level} AS MATERIALIZED (SELECT cluster_id, rep, rep_metres FROM rep{level}{more}),
est{level} AS MATERIALIZED (SELECT o.path_id, t.rep AS site_id, min(o.metres + l.metres + t.rep_metres) AS metres FROM own{level} o
  JOIN (SELECT cluster_id, nbr_id, metres FROM link{level} UNION ALL SELECT cluster_id, cluster_id, 0 FROM centre{level}) l USING (cluster_id) JOIN target{level} t ON t.cluster_id = l.nbr_id GROUP BY ALL)"""


def serving(tau: float, eps: float = 0.75, points: str = "points", existing: tuple[int, ...] = (), site: str = "true") -> tuple[str, str]:
    """The relations of the level that serves tau, and its estimates."""
    p = level_of(tau, LIMITS_100, eps)
    return level_relations(p, level_radii(LIMITS_100, eps)[p], eps, points, site=site), estimated(p, existing)


def stats(where: str = "true") -> str:
    """Rows of index statistics from the member, link and own relations of all levels; where: which paths."""
    rows = [f"""SELECT CAST({p} AS INTEGER) AS level, round({r}::DOUBLE, 6) AS radius, (SELECT count(*) FROM centre{p}) AS n_clusters, round((SELECT count(*) FROM member{p}) / (SELECT count(*) FROM centre{p}), 6) AS mean_nodes,
  round((SELECT count(*) FROM own{p} WHERE {where}) / (SELECT count(*) FROM centre{p}), 6) AS mean_paths, round((SELECT count(*) FROM link{p}) / (SELECT count(*) FROM centre{p}), 6) AS mean_links""" for p, r in enumerate(level_radii())]
    return " UNION ALL ".join(rows)


def all_levels(points: str = "points") -> list[str]:
    return [level_relations(p, r, 0.75, points) for p, r in enumerate(level_radii())]


def reps(level: int) -> str:
    return f"SELECT DISTINCT rep AS site_id FROM rep{level}"


def leaders(name: str, cover: str, threshold: float) -> str:
    """{name}(cluster_id, site_id): sites by weight, each to the first leader whose cover is similar, or a leader."""
    return f"""{name}_n AS MATERIALIZED (SELECT site_id, count(*) AS n, sum(score) AS w FROM {cover} GROUP BY site_id),
{name}_p AS MATERIALIZED (SELECT x.site_id AS a, y.site_id AS b, count(*) AS c FROM {cover} x JOIN {cover} y ON x.path_id = y.path_id AND x.site_id <> y.site_id GROUP BY ALL),
{name}_o AS MATERIALIZED (SELECT s.site_id, row_number() OVER (ORDER BY s.w DESC, s.site_id) AS i, (SELECT list(b) FROM {name}_p q JOIN {name}_n v ON v.site_id = q.b WHERE q.a = s.site_id AND q.c >= {threshold} * (s.n + v.n - q.c)) AS near FROM {name}_n s),
{name}_r(i, site_id, cluster_id, heads) AS (
  SELECT CAST(0 AS BIGINT), CAST(-1 AS BIGINT), CAST(-1 AS BIGINT), CAST([] AS BIGINT[])
  UNION ALL
  SELECT o.i, o.site_id, coalesce(list_filter(r.heads, lambda h: list_contains(o.near, h))[1], o.site_id),
    CASE WHEN len(list_filter(r.heads, lambda h: list_contains(o.near, h))) > 0 THEN r.heads ELSE list_append(r.heads, o.site_id) END
  FROM {name}_r r JOIN {name}_o o ON o.i = r.i + 1
),
{name} AS MATERIALIZED (SELECT cluster_id, site_id FROM {name}_r WHERE i > 0)"""


#: The 100-node lattice with day trips as they are, and filled.
DAYS = (lattice(100), DIST, TRIPS, DAY_POINTS, detour())
FILLED = (lattice(100), DIST, TRIPS, DAY_POINTS, filled(10), detour("any", "filled_points"))


def statement(world: tuple[str, ...], *parts: str) -> str:
    """The relations of a world and more, and the last part as the query over them."""
    return chain(*world, *parts[:-1]) + parts[-1]
