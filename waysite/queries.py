"""The queries of the placement engine: networks, paths, distances, covers, placements, sketches, index, updates."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from waysite import fixtures as fx
from waysite import measures as ms
from waysite.functions import preference as pref
from waysite.operators import baselines as bl
from waysite.operators import clusters as cl
from waysite.operators import detours as dt
from waysite.operators import exact as ex
from waysite.operators import greedy as gr
from waysite.operators import index as ix
from waysite.operators import network as nw
from waysite.operators import paths as pt
from waysite.operators import sketch as sk
from waysite.operators.distance import frontier_distances, heap_distances, network_distances, reverse, round_trip, search_horizon
from waysite.oracles import placed_sql as ps
from waysite.oracles import placement_sql as sql
from waysite.sources.tables import materialize, read_table

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
TAU, K = fx.TAU, fx.K


def query(oracle: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if oracle:
            ORACLES[f.__name__] = oracle
        return f

    return add


def placed(spark: SparkSession, p: gr.Placement) -> DataFrame:
    return p.frame(spark)


def base(*parts: str) -> str:
    return sql.chain(sql.lattice(100), sql.DIST, *parts)


def over_events(*parts: str) -> str:
    """As base, with the nodes that events visit for the network's."""
    return sql.chain(sql.lattice_over(sql.VISITED), *parts)


def visited_net(spark: SparkSession, sf_dir: str) -> nw.Network:
    return fx.net100(spark, sf_dir).given_net(lambda: fx.visited_nodes(spark, sf_dir))


def home_net(spark: SparkSession, sf_dir: str) -> nw.Network:
    return fx.net25(spark, sf_dir).given_net(lambda: fx.home_nodes(spark, sf_dir))


# -- networks and paths


@query(sql.chain(sql.lattice_over(sql.HOMES)) + "SELECT src, dst, CAST(metres AS INTEGER) AS metres FROM edges")
def net25_edges(spark, sf_dir):
    return home_net(spark, sf_dir).edges


@query(over_events() + "SELECT src, dst, CAST(metres AS INTEGER) AS metres FROM edges")
def net100_edges(spark, sf_dir):
    return visited_net(spark, sf_dir).edges


@query("SELECT (SELECT count(*) FROM range(100) a(i) WHERE i % 10 < 9) + (SELECT count(*) FROM range(90)) AS mesh_roads, 9 * 10 + 9 AS star_roads, 4 * (5 * 4 * 2) + 6 AS poly_roads")
def network_shapes(spark, sf_dir):
    ids = nw.id_range(spark, 100)
    counts = [nw.build_network(ids, 100, s).edges.count() // 2 for s in ("mesh", "star", "poly")]
    return spark.createDataFrame([tuple(counts)], "mesh_roads long, star_roads long, poly_roads long")


@query(sql.chain(sql.lattice(25)) + """SELECT src, dst, CAST(metres AS INTEGER) AS metres FROM edges WHERE NOT ((src = 0 AND dst = 1) OR (src = 1 AND dst = 0))
UNION ALL SELECT 0, 25, 40 UNION ALL SELECT 25, 1, m - 40 FROM (SELECT metres AS m FROM edges WHERE src = 0 AND dst = 1)
UNION ALL SELECT 1, 25, b - CAST(round(b * 40 / m) AS INTEGER) FROM (SELECT (SELECT metres FROM edges WHERE src = 0 AND dst = 1) AS m, (SELECT metres FROM edges WHERE src = 1 AND dst = 0) AS b)
UNION ALL SELECT 25, 0, CAST(round(b * 40 / m) AS INTEGER) FROM (SELECT (SELECT metres FROM edges WHERE src = 0 AND dst = 1) AS m, (SELECT metres FROM edges WHERE src = 1 AND dst = 0) AS b)""")
def split_edge(spark, sf_dir):
    return nw.split_edge(fx.net25(spark, sf_dir).net(), 0, 1, 40, 25).edges


@query(sql.chain(sql.DAY_POINTS) + "SELECT path_id, seq, node_id FROM points")
def trips_by_day(spark, sf_dir):
    return fx.net100(spark, sf_dir).points().select("path_id", "seq", "node_id")


@query(sql.chain(sql.VISITS) + """, opened AS (SELECT *, coalesce(CAST(floor(epoch(ts)) AS BIGINT) - CAST(floor(epoch(lag(ts) OVER w)) AS BIGINT) > 21600, false) AS new FROM visits WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
t AS (SELECT *, user_id * 10000 + CAST(sum(CAST(new AS INTEGER)) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS path_id FROM opened)
SELECT path_id, CAST(row_number() OVER (PARTITION BY path_id ORDER BY ts, event_id) - 1 AS INTEGER) AS seq, node_id FROM t""")
def trips_by_session(spark, sf_dir):
    return pt.trips_by_session(read_table(spark, sf_dir, "events", "user_id", "ts", "event_id", "props")).select("path_id", "seq", "node_id")


@query(sql.chain(sql.DAY_POINTS, sql.filled(10)) + "SELECT path_id, seq, node_id FROM filled_points")
def paths_filled(spark, sf_dir):
    return fx.net100(spark, sf_dir, filled=True).points().select("path_id", "seq", "node_id")


@query(base(sql.DAY_POINTS) + """, lagged AS (SELECT path_id, seq, node_id, lag(node_id) OVER (PARTITION BY path_id ORDER BY seq) AS last FROM points),
asked AS (SELECT DISTINCT last AS u, node_id AS v FROM lagged WHERE last <> node_id),
hop AS MATERIALIZED (SELECT a.u, a.v, min(e.dst) AS n FROM (SELECT d.src AS u, d.dst AS v, d.metres FROM dist d WHERE d.src <> d.dst) a JOIN edges e ON e.src = a.u JOIN dist r ON r.src = e.dst AND r.dst = a.v AND e.metres + r.metres = a.metres GROUP BY ALL),
walk(u, v, sub, spot) AS (SELECT u, v, 0, u FROM asked UNION ALL SELECT w.u, w.v, w.sub + 1, h.n FROM walk w JOIN hop h ON h.u = w.spot AND h.v = w.v WHERE w.spot <> w.v),
steps AS (SELECT l.path_id, l.seq, coalesce(w.sub, 0) AS sub, coalesce(w.spot, l.node_id) AS node_id FROM lagged l LEFT JOIN walk w ON w.u = l.last AND w.v = l.node_id AND w.sub > 0)
SELECT path_id, CAST(row_number() OVER (PARTITION BY path_id ORDER BY seq, sub) - 1 AS INTEGER) AS seq, CAST(node_id AS BIGINT) AS node_id FROM steps""")
def paths_filled_shortest(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return pt.fill_gaps(w.points(), rule="shortest", edges=w.net().edges).select("path_id", "seq", "node_id")


@query(sql.chain(sql.DAY_POINTS) + "SELECT path_id // 100 AS path_id, CAST(row_number() OVER (PARTITION BY path_id // 100 ORDER BY path_id, seq) - 1 AS INTEGER) AS seq, node_id FROM points")
def paths_by_user(spark, sf_dir):
    return fx.net100u(spark, sf_dir).points().select("path_id", "seq", "node_id")


@query(sql.chain(sql.NATION_POINTS) + "SELECT path_id, seq, node_id FROM points")
def paths_by_order(spark, sf_dir):
    return fx.net25(spark, sf_dir).points().select("path_id", "seq", "node_id")


@query(sql.chain(sql.VISITS) + "SELECT event_id, node_id FROM visits")
def map_matched(spark, sf_dir):
    raw = pt.raw_points(read_table(spark, sf_dir, "events", "user_id", "ts", "event_id", "props"))
    return pt.map_match(raw, fx.net100(spark, sf_dir).net().nodes, "event_id")


@query("SELECT c_custkey AS path_id, CAST(0 AS INTEGER) AS seq, c_custkey % 100 AS node_id FROM customer")
def static_paths(spark, sf_dir):
    return fx.static100(spark, sf_dir).points().select("path_id", "seq", "node_id")


# -- distances and detours

ALL_DISTANCES = "SELECT src, dst, metres FROM dist"


@query(sql.chain(sql.lattice(25), sql.DIST) + ALL_DISTANCES)
def distances_net25(spark, sf_dir):
    net = fx.net25(spark, sf_dir).net()
    return frontier_distances(net.edges, net.nodes, None)


@query(over_events(sql.DIST) + ALL_DISTANCES)
def distances_net100(spark, sf_dir):
    net = visited_net(spark, sf_dir)
    return network_distances(net.edges, net.nodes)


@query(over_events(sql.DIST) + "SELECT src, dst, metres FROM dist WHERE metres <= 400")
def distances_horizon(spark, sf_dir):
    net = visited_net(spark, sf_dir)
    return heap_distances(net.edges, net.nodes, 400)


@query(base() + "SELECT dst AS src, src AS dst, metres FROM dist")
def distances_reverse(spark, sf_dir):
    net = fx.net100(spark, sf_dir).net()
    return network_distances(reverse(net.edges), net.nodes)


@query(base(sql.TRIPS) + "SELECT a, b, metres FROM round_trips")
def round_trips(spark, sf_dir):
    return fx.net100(spark, sf_dir).trips()


@query(base() + ALL_DISTANCES)
def distances_relational(spark, sf_dir):
    net = fx.net100(spark, sf_dir).net()
    return network_distances(net.edges, net.nodes, engine="relational")


@query(base(sql.DAY_POINTS) + "SELECT DISTINCT src, dst, metres FROM points a JOIN points b USING (path_id) JOIN dist ON src = a.node_id AND dst = b.node_id")
def distances_wanted(spark, sf_dir):
    """Only between nodes of one path."""
    w = fx.net100(spark, sf_dir)
    nodes = w.points().select("path_id", "node_id")
    pairs = nodes.join(nodes.withColumnRenamed("node_id", "to"), "path_id").select(F.col("node_id").alias("src"), F.col("to").alias("dst"))
    return network_distances(w.net().edges, nodes, wanted=pairs)


@query(base(sql.DAY_POINTS, sql.detour()) + "SELECT path_id, site_id, metres FROM detour")
def detour_any(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return dt.detours(w.points(), w.sites(), w.dist())


@query(base(sql.DAY_POINTS, sql.detour()) + "SELECT path_id, site_id, metres FROM detour")
def detour_any_kernel(spark, sf_dir):
    return fx.net100(spark, sf_dir).detours()


@query(base(sql.DAY_POINTS, sql.detour("same")) + "SELECT path_id, site_id, metres FROM detour")
def detour_same(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return dt.detours(w.points(), w.sites(), w.dist(), "same")


@query(base(sql.DAY_POINTS, sql.detour("forward")) + "SELECT path_id, site_id, metres FROM detour")
def detour_forward(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return dt.detours(w.points(), w.sites(), w.dist(), "forward")


@query(base(sql.DAY_POINTS) + """, steps AS (SELECT path_id, seq, node_id, lag(node_id) OVER (PARTITION BY path_id ORDER BY seq) AS last FROM points),
along AS (SELECT s.path_id, s.seq, s.node_id, sum(coalesce(d.metres, 0)) OVER (PARTITION BY path_id ORDER BY seq ROWS UNBOUNDED PRECEDING) AS p FROM steps s LEFT JOIN dist d ON d.src = s.last AND d.dst = s.node_id),
ways AS (SELECT a.path_id, t.dst AS site_id, b.metres - a.p + min(t.metres + a.p) OVER (PARTITION BY a.path_id, t.dst ORDER BY a.seq ROWS UNBOUNDED PRECEDING) AS extra FROM along a JOIN dist t ON t.src = a.node_id JOIN dist b ON b.src = t.dst AND b.dst = a.node_id)
SELECT path_id, site_id, CAST(greatest(min(extra), 0) AS BIGINT) AS metres FROM ways GROUP BY ALL""")
def detour_forward_along(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return dt.detours(w.points(), w.sites(), w.dist(), "forward_along")


@query(base(sql.DAY_POINTS, sql.detour()) + """SELECT path_id, site_id, metres, CAST(row_number() OVER (PARTITION BY site_id ORDER BY metres, path_id) AS INTEGER) AS site_rank,
CAST(row_number() OVER (PARTITION BY path_id ORDER BY metres, site_id) AS INTEGER) AS path_rank FROM detour""")
def ranked_detours(spark, sf_dir):
    return dt.ranked_detours(fx.net100(spark, sf_dir).detours())


@query(base(sql.DAY_POINTS) + "SELECT 400 + max(d.metres) AS horizon FROM points a JOIN points b USING (path_id) JOIN dist d ON d.src = a.node_id AND d.dst = b.node_id")
def search_horizon_any(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return spark.createDataFrame([(search_horizon(400, w.points(), w.dist()),)], "horizon long")


# -- covers

COVER_ROWS = "SELECT path_id, site_id, metres, score FROM cover"


@query(sql.chain(*sql.day_cover()) + COVER_ROWS)
def cover_binary(spark, sf_dir):
    return fx.net100(spark, sf_dir).cover(pref.binary(TAU))


@query(sql.chain(*sql.day_cover(preference="linear")) + COVER_ROWS)
def cover_linear(spark, sf_dir):
    return fx.net100(spark, sf_dir).cover(pref.linear(TAU))


@query(sql.chain(*sql.day_cover(preference="convex")) + COVER_ROWS)
def cover_convex(spark, sf_dir):
    return fx.net100(spark, sf_dir).cover(pref.convex(TAU))


@query(sql.chain(*sql.day_cover(preference="exponential")) + COVER_ROWS)
def cover_exponential(spark, sf_dir):
    return fx.net100(spark, sf_dir).cover(pref.exponential(TAU))


@query(base(sql.DAY_POINTS, sql.detour()) + "SELECT * FROM (SELECT path_id, site_id, metres, CAST(round((1 / (1 + metres / 100.0::DOUBLE)) * 1000000) AS BIGINT) AS score FROM detour WHERE metres <= 400) c WHERE score > 0")
def cover_custom(spark, sf_dir):
    return fx.net100(spark, sf_dir).cover(pref.custom(TAU, lambda d: 1 / (1 + d / 100)))


@query(sql.chain(*sql.day_cover()) + COVER_ROWS)
def cover_at_query(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return dt.cover_at_query(w.net().edges, w.points(), w.sites(), TAU, pref.binary(TAU))


@query(sql.chain(*sql.day_cover()) + "SELECT site_id, CAST(sum(score) AS BIGINT) AS weight, count(*) AS n_paths FROM cover GROUP BY site_id")
def site_weights(spark, sf_dir):
    return dt.site_weights(fx.net100(spark, sf_dir).cover(pref.binary(TAU)))


@query(sql.chain(*sql.day_cover(240)) + "SELECT path_id, string_agg(CAST(site_id AS VARCHAR), ',' ORDER BY metres, site_id) AS members FROM cover GROUP BY path_id")
def covering_sets(spark, sf_dir):
    sets = dt.covering_sets(fx.net100(spark, sf_dir).cover(pref.binary(240)), "path_id")
    return sets.select("path_id", F.array_join(F.transform("members", lambda x: x.cast("string")), ",").alias("members"))


@query(base(sql.TRIPS) + "SELECT round(avg(n), 6) AS mean_sites FROM (SELECT a, sum(CAST(metres <= 800 AS INTEGER)) AS n FROM round_trips WHERE a <> b GROUP BY a) s")
def sites_within_tau(spark, sf_dir):
    return ms.sites_within(fx.net100(spark, sf_dir).trips(), 800)


# -- greedy family


def greedy(spark, sf_dir, preference, **options) -> gr.Placement:
    w = fx.net100(spark, sf_dir)
    spec = gr.PlacementSpec(**({"k": K} | options))
    return gr.greedy_place(w.cover(preference), spec, w.n_paths(), w.sites())


PLACED5 = sql.chain(*sql.day_cover(), sql.greedy(5)) + sql.PLACED


@query(PLACED5)
def greedy_binary(spark, sf_dir):
    return placed(spark, greedy(spark, sf_dir, pref.binary(TAU)))


@query(PLACED5)
def greedy_delta(spark, sf_dir):
    return placed(spark, greedy(spark, sf_dir, pref.binary(TAU), mode="delta"))


@query(PLACED5)
def greedy_lazy(spark, sf_dir):
    return placed(spark, greedy(spark, sf_dir, pref.binary(TAU), mode="lazy"))


@query(sql.chain(*sql.day_cover(preference="convex"), sql.greedy(5)) + sql.PLACED)
def greedy_convex(spark, sf_dir):
    return placed(spark, greedy(spark, sf_dir, pref.convex(TAU)))


@query(sql.chain(sql.lattice(100), sql.DIST, sql.DAY_POINTS, sql.filled(10), sql.detour("any", "filled_points"), sql.cover(400), sql.greedy(5)) + sql.PLACED)
def greedy_filled(spark, sf_dir):
    w = fx.net100(spark, sf_dir, filled=True)
    return placed(spark, gr.greedy_place(w.cover(pref.binary(TAU)), gr.PlacementSpec(k=5), w.n_paths(), w.sites()))


SHARES = "round(1000000 * (l_quantity / (max(l_quantity) OVER (PARTITION BY l_orderkey) + 1)))"


@query(f"""WITH RECURSIVE lines AS (SELECT l_orderkey AS path_id, s_nationkey AS site_id, {SHARES} AS score FROM lineitem JOIN supplier ON l_suppkey = s_suppkey), cover AS MATERIALIZED (SELECT path_id, CAST(site_id AS BIGINT) AS site_id, CAST(max(score) AS BIGINT) AS score FROM lines GROUP BY ALL), points AS (SELECT path_id FROM cover),
""" + ps.steps("g", "cover", 2, "SELECT DISTINCT site_id FROM cover") + " " + ps.placed("g"))
def greedy_from_scores(spark, sf_dir):
    """A placement over scores as a table has them, without any network: what an order's largest line from a nation is of the
    order's largest line."""
    lines = read_table(spark, sf_dir, "lineitem", "l_orderkey", "l_suppkey", "l_quantity").join(read_table(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    share = F.round(1_000_000 * (F.col("l_quantity") / (F.max("l_quantity").over(Window.partitionBy("l_orderkey")) + 1)))
    scored = lines.select(F.col("l_orderkey").alias("path_id"), F.col("s_nationkey").cast("long").alias("site_id"), share.alias("score"))
    cover = materialize(scored.groupBy("path_id", "site_id").agg(F.max("score").cast("long").alias("score")), "order-scores")
    return placed(spark, gr.greedy_place(cover, gr.PlacementSpec(k=2, mode="auto"), cover.select("path_id").distinct().count()))


@query(sql.chain(*sql.day_cover(), sql.greedy(5, existing=(55, 23))) + sql.PLACED)
def greedy_existing(spark, sf_dir):
    return placed(spark, greedy(spark, sf_dir, pref.binary(TAU), existing=(55, 23)))


@query(PLACED5)
def greedy_continued(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    cover = w.cover(pref.binary(TAU))
    first = gr.greedy_place(cover, gr.PlacementSpec(k=3), w.n_paths(), w.sites())
    return placed(spark, gr.continue_placement(cover, first, 5, w.n_paths()))


@query(sql.chain(*sql.day_cover(), sql.greedy(6)) + """, run AS (SELECT step, site_id, gain, CAST(sum(gain) OVER (ORDER BY step) AS BIGINT) AS utility, (SELECT count(DISTINCT path_id) FROM points) AS m FROM picks)
SELECT step, site_id, gain, utility, round(utility / 1000000 / m * 100, 6) AS utility_pct FROM run WHERE utility - gain < ceil(0.75 * m) * 1000000""")
def greedy_quota(spark, sf_dir):
    return placed(spark, greedy(spark, sf_dir, pref.binary(TAU), k=None, quota=0.75))


@query(ps.statement(ps.DAYS, ps.cover("cov", 400), ps.budget_steps("g", "cov", ps.attributed(0.6), 5.0), ps.placed("g")))
def greedy_budget(spark, sf_dir):
    return placed(spark, budget_place(spark, sf_dir, 0.6, True))


@query(ps.statement(ps.DAYS, ps.cover("cov", 400), ps.budget_steps("g", "cov", ps.attributed(0.6), 5.0, False), ps.placed("g")))
def greedy_budget_nosafe(spark, sf_dir):
    return placed(spark, budget_place(spark, sf_dir, 0.6, False))


@query(PLACED5)
def greedy_budget_unit(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return placed(spark, gr.greedy_place(w.cover(pref.binary(TAU)), gr.PlacementSpec(k=None, budget=5.0), w.n_paths(), fx.with_costs(w.sites(), 0.0)))


def budget_place(spark, sf_dir, sigma: float, safeguard: bool, world=None, budget: float = 5.0) -> gr.Placement:
    w = world or fx.net100(spark, sf_dir)
    return gr.greedy_place(w.cover(pref.binary(TAU)), gr.PlacementSpec(k=None, budget=budget, safeguard=safeguard), w.n_paths(), fx.with_costs(w.sites(), sigma))


TENTH = "0.1::DOUBLE * (SELECT count(DISTINCT path_id) FROM {})"


@query(ps.statement(ps.DAYS, ps.cover("cov", 400), ps.steps("g", "cov", 5, ps.attributed(mean=TENTH.format("points")), capacity=True), ps.placed("g")))
def greedy_capacity(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return placed(spark, gr.greedy_place(w.cover(pref.binary(TAU)), gr.PlacementSpec(k=5, capacity=True), w.n_paths(), fx.with_capacities(w.sites(), 0.1 * w.n_paths())))


@query(PLACED5)
def greedy_capacity_unlimited(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return placed(spark, gr.greedy_place(w.cover(pref.binary(TAU)), gr.PlacementSpec(k=5, capacity=True), w.n_paths(), w.sites()))


@query()
def greedy_budget_capacity(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    sites = fx.with_capacities(fx.with_costs(w.sites(), 0.4), 0.1 * w.n_paths())
    return placed(spark, gr.greedy_place(w.cover(pref.binary(TAU)), gr.PlacementSpec(k=None, budget=5.0, capacity=True), w.n_paths(), sites))


@query(base(sql.DAY_POINTS, sql.detour()) + """, cover AS MATERIALIZED (SELECT path_id, site_id, max(metres) OVER (PARTITION BY path_id) + 1 - metres AS score FROM detour),
""" + sql.greedy(3) + """ SELECT step, site_id, gain, CAST((SELECT sum(w) FROM (SELECT max(metres) + 1 AS w FROM detour GROUP BY path_id) x) - sum(gain) OVER (ORDER BY step) AS BIGINT) AS total_metres FROM picks""")
def greedy_inconvenience(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return gr.place_inconvenience(w.detours(), 3, w.n_paths(), w.sites())[1]


# -- exact and baselines

NET25 = sql.chain(sql.lattice(25), sql.DIST, sql.NATION_POINTS, sql.detour(), sql.cover(240))


@query(NET25 + """, sets AS (SELECT a.node_id AS s1, b.node_id AS s2 FROM nodes a JOIN nodes b ON a.node_id < b.node_id),
best AS (SELECT s1, s2, path_id, max(score) AS u FROM sets JOIN cover ON site_id IN (s1, s2) GROUP BY ALL)
SELECT s1, s2, CAST(sum(u) AS BIGINT) AS utility FROM best GROUP BY s1, s2 ORDER BY utility DESC, s1, s2 LIMIT 1""")
def optimal_net25(spark, sf_dir):
    w = fx.net25(spark, sf_dir).by_routes()
    p = ex.optimal_placement(w.cover(pref.binary(240)), w.sites(), 2, w.n_paths(), "branch_bound")
    return spark.createDataFrame([(*sorted(p.sites), p.utility)], "s1 long, s2 long, utility long")


@query(NET25 + """, sets AS (SELECT a.node_id AS s1, b.node_id AS s2 FROM nodes a JOIN nodes b ON a.node_id < b.node_id),
best AS (SELECT s1, s2, path_id, max(score) AS u FROM sets JOIN cover ON site_id IN (s1, s2) GROUP BY ALL)
SELECT s1, s2, CAST(sum(u) AS BIGINT) AS utility FROM best GROUP BY s1, s2""")
def all_pairs_net25(spark, sf_dir):
    w = fx.net25(spark, sf_dir).by_routes()
    sets = ex.enumerate_sets(w.cover(pref.binary(240)), w.sites(), 2)
    return sets.select(F.col("members")[0].alias("s1"), F.col("members")[1].alias("s2"), "utility")


@query(NET25 + "SELECT kind, count(*) AS n, CAST(sum(coefficient) AS BIGINT) AS total FROM (SELECT 'objective' AS kind, score AS coefficient FROM cover UNION ALL SELECT 'open', 1 FROM cover UNION ALL SELECT 'open', -1 FROM cover UNION ALL SELECT 'once', 1 FROM cover UNION ALL SELECT 'count', 1 FROM nodes) r GROUP BY kind")
def ilp_rows_net25(spark, sf_dir):
    w = fx.net25(spark, sf_dir)
    return ex.ilp_rows(w.cover(pref.binary(240)), w.sites(), 2).groupBy("kind").agg(F.count("*").alias("n"), F.sum("coefficient").alias("total"))


@query(sql.chain(*sql.day_cover()) + """, w AS (SELECT site_id, sum(score) AS weight FROM cover GROUP BY site_id), top AS (SELECT row_number() OVER (ORDER BY weight DESC, site_id DESC) AS step, site_id FROM w ORDER BY weight DESC, site_id DESC LIMIT 5),
first AS (SELECT c.path_id, min(t.step) AS step FROM cover c JOIN top t USING (site_id) GROUP BY c.path_id)
SELECT CAST(t.step AS INTEGER) AS step, t.site_id, CAST(count(f.path_id) * 1000000 AS BIGINT) AS gain FROM top t LEFT JOIN first f USING (step) GROUP BY t.step, t.site_id""")
def top_weight(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return placed(spark, bl.top_weight_place(w.cover(pref.binary(TAU)), 5, w.n_paths())).select("step", "site_id", "gain")


STATIC = "homes AS MATERIALIZED (SELECT c_custkey AS path_id, c_custkey % 100 AS node_id FROM customer), still AS MATERIALIZED (SELECT h.path_id, r.b AS site_id, r.metres FROM homes h JOIN round_trips r ON r.a = h.node_id)"


@query(ps.statement(ps.DAYS, ps.cover("cov", 400), STATIC, ps.cover("home", 400, source="still"), ps.steps("h", "home", 5, "SELECT DISTINCT site_id FROM home"), ps.steps("g", "cov", 5, forced="h"), ps.placed("g")))
def static_place(spark, sf_dir):
    w, still = fx.net100(spark, sf_dir), fx.static100(spark, sf_dir)
    return placed(spark, bl.static_place(still.detours(), w.cover(pref.binary(TAU)), pref.binary(TAU), 5, w.n_paths()))


@query(sql.chain(*sql.day_cover(4034)) + ", first AS (SELECT path_id, min(site_id) AS s FROM cover WHERE site_id < 3 GROUP BY path_id) SELECT CAST(i + 1 AS INTEGER) AS step, CAST(i AS BIGINT) AS site_id, CAST(count(s) * 1000000 AS BIGINT) AS gain FROM range(3) r(i) LEFT JOIN first ON s = i GROUP BY i")
def arbitrary_place(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return placed(spark, bl.arbitrary_place(w.sites(), w.cover(pref.binary(4034)), 3, w.n_paths())).select("step", "site_id", "gain")


@query(ps.statement(ps.DAYS, ps.cover("cov", 400), "h AS MATERIALIZED (SELECT row_number() OVER (ORDER BY md5('1:' || node_id)) AS step, node_id AS site_id FROM nodes)", *(f"h_pick{i} AS (SELECT site_id FROM h WHERE step = {i})" for i in range(1, 6)), ps.steps("g", "cov", 5, forced="h"), ps.placed("g")))
def random_place(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return placed(spark, bl.random_place(w.sites(), w.cover(pref.binary(TAU)), 5, w.n_paths()))


# -- sketches


@query(sql.chain(*sql.day_cover(), sql.fm_words(8)) + "SELECT site_id, copy, word FROM words")
def fm_words(spark, sf_dir):
    return sk.fm_sketch(fx.net100(spark, sf_dir).cover(pref.binary(TAU)), "site_id", "path_id", 8)


@query(sql.chain(*sql.day_cover(), sql.fm_words(8)) + "SELECT site_id, pow(2.0, sum(bit_count(~word & (word + 1)) * 0 + bit_count((~word & (word + 1)) - 1)) / count(*)) / 0.77351 AS estimate FROM words GROUP BY site_id")
def fm_estimates(spark, sf_dir):
    return sk.fm_estimate(sk.fm_sketch(fx.net100(spark, sf_dir).cover(pref.binary(TAU)), "site_id", "path_id", 8), "site_id")


@query(sql.chain(*sql.day_cover(), sql.fm_words(8)) + "SELECT site_id, pow(2.0, sum(length(bin(word))) / count(*)) AS estimate FROM words GROUP BY site_id")
def fm_estimates_last_set(spark, sf_dir):
    return sk.fm_estimate(sk.fm_sketch(fx.net100(spark, sf_dir).cover(pref.binary(TAU)), "site_id", "path_id", 8), "site_id", "last_set")


@query(sql.chain(*sql.day_cover(), sql.fm_words(8)) + "SELECT copy, bit_or(word) AS word FROM words GROUP BY copy")
def fm_union(spark, sf_dir):
    return sk.fm_union(sk.fm_sketch(fx.net100(spark, sf_dir).cover(pref.binary(TAU)), "site_id", "path_id", 8), "site_id")


FM_PLACED = ps.statement(ps.DAYS, ps.cover("cov", 400), ps.sketch_steps("f", "cov", 5, 30), ps.steps("g", "cov", 5, forced="f"), ps.placed("g"))


@query(FM_PLACED)
def greedy_fm(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return placed(spark, sk.greedy_place_sketch(w.cover(pref.binary(TAU)), K, w.n_paths(), fx.COPIES, prune=False))


@query(FM_PLACED)
def greedy_fm_pruned(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return placed(spark, sk.greedy_place_sketch(w.cover(pref.binary(TAU)), K, w.n_paths(), fx.COPIES, prune=True))


# -- clusters and index

R2 = 210 * 1.75 * 1.75 / 4


@query(base(sql.TRIPS) + f"SELECT a AS node, b AS dominated, metres FROM round_trips WHERE metres <= {2 * R2}")
def dominating_sets(spark, sf_dir):
    return cl.dominating_sets(fx.net100(spark, sf_dir).trips(), R2)


@query(base(sql.TRIPS, sql.clusters(R2)) + "SELECT cluster_id, node_id, metres FROM member")
def clusters_level2(spark, sf_dir):
    return cl.dominating_clusters(cl.dominating_sets(fx.net100(spark, sf_dir).trips(), R2), "driver")


@query(base(sql.TRIPS, sql.clusters(R2)) + "SELECT cluster_id, node_id, metres FROM member")
def clusters_by_peers(spark, sf_dir):
    return cl.dominating_clusters(cl.dominating_sets(fx.net100(spark, sf_dir).trips(), R2), "peers")


@query()
def clusters_by_sketch(spark, sf_dir):
    return cl.dominating_clusters(cl.dominating_sets(fx.net100(spark, sf_dir).trips(), R2), sketch_copies=fx.COPIES)


def quarter_sites(w: fx.World) -> DataFrame:
    return w.sites().where(F.col("site_id") % 4 == 0)


@query(base(sql.TRIPS, sql.clusters(R2)) + "SELECT cluster_id, arg_min(node_id, struct_pack(metres, node_id)) FILTER (WHERE node_id % 4 = 0) AS rep FROM member GROUP BY cluster_id")
def representatives_closest(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    member = w.index().member.where("level = 2")
    return ix.representatives(member, quarter_sites(w)).select("cluster_id", "rep")


@query(base(sql.TRIPS, sql.clusters(R2), sql.DAY_POINTS) + ", v AS (SELECT node_id, count(DISTINCT path_id) AS n FROM points GROUP BY node_id) SELECT cluster_id, arg_min(node_id, struct_pack(o := -coalesce(n, 0), i := node_id)) FILTER (WHERE node_id % 4 = 0) AS rep FROM member LEFT JOIN v USING (node_id) GROUP BY cluster_id")
def representatives_busiest(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    visits = w.points().groupBy("node_id").agg(F.countDistinct("path_id").alias("n"))
    return ix.representatives(w.index().member.where("level = 2"), quarter_sites(w), "busiest", visits).select("cluster_id", "rep")


@query(base(sql.TRIPS, sql.clusters(R2), sql.DAY_POINTS, sql.detour()) + "SELECT DISTINCT m.cluster_id, p.path_id, d.metres FROM points p JOIN member m USING (node_id) JOIN detour d ON d.path_id = p.path_id AND d.site_id = m.cluster_id")
def cluster_paths(spark, sf_dir):
    return fx.net100(spark, sf_dir).index().path.where("level = 2").select("cluster_id", "path_id", "metres")


@query(over_events(sql.DIST, sql.TRIPS, sql.clusters(R2)) + f", c AS (SELECT DISTINCT cluster_id FROM member) SELECT a AS cluster_id, b AS nbr_id, metres FROM round_trips JOIN c x ON x.cluster_id = a JOIN c y ON y.cluster_id = b WHERE a <> b AND metres <= {4 * R2 * 1.75}")
def cluster_links(spark, sf_dir):
    net = visited_net(spark, sf_dir)
    trips = materialize(round_trip(network_distances(net.edges, net.nodes)), "trips")
    level = ix.Level(0, R2, 4 * R2, 4 * R2 * (1 + fx.EPS))
    return ix.cluster_links(materialize(ix.clustered(trips, (level,)), "member"), trips, (level,), fx.EPS).select("cluster_id", "nbr_id", "metres")


@query(base(sql.TRIPS, sql.clusters(R2), sql.DAY_POINTS) + """, s AS (SELECT path_id, seq, cluster_id, lag(cluster_id) OVER (PARTITION BY path_id ORDER BY seq) AS last FROM points JOIN member USING (node_id))
SELECT path_id, CAST(row_number() OVER (PARTITION BY path_id ORDER BY seq) - 1 AS INTEGER) AS seq, cluster_id FROM s WHERE last IS NULL OR last <> cluster_id""")
def compressed_paths(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return ix.compress_paths(w.points(), w.index().member.where("level = 2")).select("path_id", "seq", "cluster_id")


@query(base(sql.TRIPS) + """, lim AS (SELECT min(metres) AS lo, max(metres) AS hi FROM round_trips WHERE a <> b), plan(level, tau_lo) AS (SELECT 0, CAST(lo AS DOUBLE) FROM lim UNION ALL SELECT level + 1, tau_lo * 1.75 FROM plan, lim WHERE tau_lo * 1.75 <= hi)
SELECT CAST(level AS INTEGER) AS level, round(tau_lo / 4, 6) AS radius, round(tau_lo, 6) AS tau_lo, round(tau_lo * 1.75, 6) AS tau_hi FROM plan""")
def level_plan(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    rows = [(v.level, round(v.radius, 6), round(v.tau_lo, 6), round(v.tau_hi, 6)) for v in ix.level_plan(*ix.tau_limits(w.trips(), w.sites()), fx.EPS)]
    return spark.createDataFrame(rows, "level int, radius double, tau_lo double, tau_hi double")


@query(ps.statement(ps.FILLED, *ps.all_levels("filled_points"), ps.stats()))
def index_stats(spark, sf_dir):
    return ix.index_stats(fx.net100(spark, sf_dir, filled=True).index())


@query()
def index_cost(spark, sf_dir):
    """Rows a level, and the bytes of all files."""
    index = fx.net100(spark, sf_dir, filled=True).index()
    return ms.index_rows(index).withColumn("index_bytes", F.lit(ms.index_bytes(index)))


EST = (sql.TRIPS, sql.clusters(R2), sql.DAY_POINTS, sql.detour(), f"""cs AS (SELECT DISTINCT cluster_id FROM member), links AS (SELECT a AS src, b AS dst, metres FROM round_trips JOIN cs x ON x.cluster_id = a JOIN cs y ON y.cluster_id = b WHERE a = b OR metres <= {4 * R2 * 1.75}),
own AS (SELECT DISTINCT m.cluster_id, p.path_id, d.metres FROM points p JOIN member m USING (node_id) JOIN detour d ON d.path_id = p.path_id AND d.site_id = m.cluster_id),
est AS MATERIALIZED (SELECT o.path_id, l.dst AS site_id, min(o.metres + l.metres) AS metres FROM own o JOIN links l ON l.src = o.cluster_id GROUP BY ALL)""")


@query(base(*EST) + "SELECT path_id, site_id, metres FROM est")
def estimated_detours(spark, sf_dir):
    return ix.estimated_detours(fx.net100(spark, sf_dir).index(), 2)


@query(base(*EST, sql.cover(800, source="est")) + COVER_ROWS)
def estimated_cover(spark, sf_dir):
    return ix.estimated_cover(fx.net100(spark, sf_dir).index(), 2, pref.binary(800))


@query("SELECT CAST(0 AS BIGINT) AS outside, CAST(0 AS BIGINT) AS below")
def estimate_subset_check(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    est = ix.estimated_cover(w.index(), 2, pref.binary(800)).select("path_id", "site_id")
    outside = est.exceptAll(w.cover(pref.binary(800)).select("path_id", "site_id")).count()
    true = w.detours().select(F.col("path_id").alias("p"), F.col("site_id").alias("s"), F.col("metres").alias("exact"))
    below = ix.estimated_detours(w.index(), 2).join(true, (F.col("path_id") == F.col("p")) & (F.col("site_id") == F.col("s"))).where("metres < exact").count()
    return spark.createDataFrame([(outside, below)], "outside long, below long")


@query(base(*EST) + "SELECT count(*) AS n, round(avg(e.metres - d.metres), 6) AS mean_excess, min(e.metres - d.metres) AS least_excess FROM est e JOIN detour d USING (path_id, site_id)")
def estimate_error(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return ms.estimate_error(ix.estimated_detours(w.index(), 2), w.detours())


@query(base(*EST, sql.cover(800, source="est")) + ", " + sql.greedy(5) + " " + sql.PLACED)
def index_place(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return placed(spark, ix.index_place(w.index(), gr.PlacementSpec(k=5), pref.binary(800), w.n_paths(), w.cover(pref.binary(800))))


AT800 = (*ps.serving(800, points="filled_points"), ps.cover("est", 800, source=f"est{ps.level_of(800)}"))
REPS800 = ps.reps(ps.level_of(800))


@query(ps.statement(ps.FILLED, *AT800, ps.sketch_steps("f", "est", 5, 30), ps.steps("g", "est", 5, REPS800, forced="f"), ps.placed("g", "filled_points")))
def index_place_fm(spark, sf_dir):
    w = fx.net100(spark, sf_dir, filled=True)
    return placed(spark, ix.index_place(w.index(), gr.PlacementSpec(k=5), pref.binary(800), w.n_paths(), sketch_copies=fx.COPIES))


@query(ps.statement(ps.FILLED, *AT800, ps.budget_steps("g", "est", f"SELECT a.* FROM ({ps.attributed(0.6)}) a SEMI JOIN ({REPS800}) r USING (site_id)", 5.0), ps.placed("g", "filled_points")))
def index_place_budget(spark, sf_dir):
    w = fx.net100(spark, sf_dir, filled=True)
    return placed(spark, ix.index_place(w.index(), gr.PlacementSpec(k=None, budget=5.0), pref.binary(800), w.n_paths(), site_table=fx.with_costs(w.sites(), 0.6)))


@query(ps.statement(ps.FILLED, *AT800, ps.steps("g", "est", 5, f"SELECT a.* FROM ({ps.attributed(mean=TENTH.format('filled_points'))}) a SEMI JOIN ({REPS800}) r USING (site_id)", capacity=True), ps.placed("g", "filled_points")))
def index_place_capacity(spark, sf_dir):
    w = fx.net100(spark, sf_dir, filled=True)
    return placed(spark, ix.index_place(w.index(), gr.PlacementSpec(k=5, capacity=True), pref.binary(800), w.n_paths(), site_table=fx.with_capacities(w.sites(), 0.1 * w.n_paths())))


EXISTING = (1, 38, 77)


@query(ps.statement(ps.DAYS, *ps.serving(800, existing=EXISTING), ps.cover("est", 800, source=f"est{ps.level_of(800)}"), ps.steps("g", "est", 5, REPS800, existing=EXISTING), ps.placed("g")))
def index_place_existing(spark, sf_dir):
    """Existing services at nodes that lead no cluster still serve their paths."""
    w = fx.net100(spark, sf_dir)
    return placed(spark, ix.index_place(w.index(), gr.PlacementSpec(k=5, existing=EXISTING), pref.binary(800), w.n_paths()))


@query(ps.statement(ps.DAYS, *ps.serving(800), ps.cover("est", 800, source=f"est{ps.level_of(800)}"), ps.steps("g", "est", 12, REPS800), """SELECT step, site_id, gain FROM (SELECT *, sum(gain) OVER (ORDER BY step) - gain AS before FROM g) r WHERE before < ceil(0.8 * (SELECT count(DISTINCT path_id) FROM points)) * 1000000"""))
def index_place_quota(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return placed(spark, ix.index_place(w.index(), gr.PlacementSpec(k=None, quota=0.8), pref.binary(800), w.n_paths())).select("step", "site_id", "gain")


ABOVE = 8000


@query(ps.statement(ps.DAYS, ps.cover("cov", ABOVE), ps.steps("g", "cov", 5, ps.attributed(mean=TENTH.format("points")), capacity=True), ps.placed("g")))
def index_place_above_range(spark, sf_dir):
    """At a threshold above the index's every site serves every path, but only up to its capacity."""
    w = fx.net100(spark, sf_dir)
    sites = fx.with_capacities(w.sites(), 0.1 * w.n_paths())
    return placed(spark, ix.index_place(w.index(), gr.PlacementSpec(k=5, capacity=True), pref.binary(ABOVE), w.n_paths(), w.cover(pref.binary(ABOVE)), None, sites))


@query(ps.statement(ps.DAYS, ps.cover("cov", ABOVE), ps.budget_steps("g", "cov", ps.attributed(0.6), 2.0), ps.placed("g")))
def index_place_above_range_budget(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return placed(spark, ix.index_place(w.index(), gr.PlacementSpec(k=None, budget=2.0), pref.binary(ABOVE), w.n_paths(), w.cover(pref.binary(ABOVE)), None, fx.with_costs(w.sites(), 0.6)))


@query(ps.statement(ps.DAYS, ps.cover("cov", 200), ps.steps("g", "cov", 5), ps.placed("g")))
def index_place_below_range(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return placed(spark, ix.index_place(w.index(), gr.PlacementSpec(k=5), pref.binary(200), w.n_paths(), w.cover(pref.binary(200))))


@query(ps.statement(ps.DAYS, *(ps.members(p, r) for p, r in enumerate(ps.level_radii((210, 1200)))), " UNION ALL ".join(f"""SELECT CAST({p} AS INTEGER) AS level, x.cluster_id, x.path_id, min(t.metres + b.metres - g.metres) AS metres FROM (SELECT DISTINCT cluster_id, path_id FROM points JOIN member{p} USING (node_id)) x
  JOIN points v ON v.path_id = x.path_id JOIN dist t ON t.src = v.node_id AND t.dst = x.cluster_id AND t.metres <= {2 * r} JOIN points w ON w.path_id = x.path_id JOIN dist b ON b.src = x.cluster_id AND b.dst = w.node_id AND b.metres <= {2 * r}
  JOIN dist g ON g.src = v.node_id AND g.dst = w.node_id GROUP BY ALL""" for p, r in enumerate(ps.level_radii((210, 1200))))))
def index_paths_bounded(spark, sf_dir):
    """The path lists of an index whose searches end at what each level needs."""
    index = fx.net100(spark, sf_dir).bounded_index((210, 1200))
    return index.path.select("level", "cluster_id", "path_id", "metres")


@query(ps.statement(ps.DAYS, *(f"{ps.members(p, r)},\ncentre{p} AS MATERIALIZED (SELECT DISTINCT cluster_id FROM member{p})" for p, r in enumerate(ps.level_radii((210, 1200)))), " UNION ALL ".join(f"SELECT CAST({p} AS INTEGER) AS level, a AS cluster_id, b AS nbr_id, metres FROM round_trips JOIN centre{p} x ON x.cluster_id = a JOIN centre{p} y ON y.cluster_id = b WHERE a <> b AND metres <= {4 * r * 1.75}" for p, r in enumerate(ps.level_radii((210, 1200))))))
def index_links_bounded(spark, sf_dir):
    index = fx.net100(spark, sf_dir).bounded_index((210, 1200))
    return index.link.select("level", "cluster_id", "nbr_id", "metres")


@query(sql.chain(*sql.day_cover(240)) + """, s AS (SELECT site_id, count(*) AS n FROM cover GROUP BY site_id), p AS (SELECT x.site_id AS a, y.site_id AS b, count(*) AS common FROM cover x JOIN cover y ON x.path_id = y.path_id AND x.site_id < y.site_id GROUP BY ALL)
SELECT a, b, common AS "both", u.n + v.n - common AS either FROM p JOIN s u ON u.site_id = a JOIN s v ON v.site_id = b WHERE common >= 0.3 * (u.n + v.n - common)""")
def jaccard_pairs(spark, sf_dir):
    return cl.similar_pairs(fx.net100(spark, sf_dir).by_routes().cover(pref.binary(240)), 0.3)


@query(ps.statement(ps.DAYS, ps.cover("cov", 240), ps.leaders("l", "cov", 0.3), "SELECT cluster_id, site_id FROM l"))
def jaccard_clusters(spark, sf_dir):
    return cl.jaccard_clusters(fx.net100(spark, sf_dir).by_routes().cover(pref.binary(240)), 0.3)


# -- updates


def quarter_index(w: fx.World) -> ix.Index:
    return fx.once(w.spark, w.sf_dir, f"index-quarter-{w.name}", lambda: ix.build_index(w.points(), quarter_sites(w), w.dist(), w.trips(), limits=ix.tau_limits(w.trips(), w.sites())))


REPS = "SELECT cluster_id, arg_min(node_id, struct_pack(metres, node_id)) FILTER (WHERE {rule}) AS rep FROM member GROUP BY cluster_id"


def level2(index: ix.Index) -> DataFrame:
    return index.clusters().where("level = 2").select("cluster_id", "rep")


@query(base(sql.TRIPS, sql.clusters(R2)) + REPS.format(rule="node_id % 4 = 0 OR node_id % 6 = 1"))
def add_sites(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return level2(ix.add_sites(quarter_index(w), w.sites().where("site_id % 6 = 1")))


@query(base(sql.TRIPS, sql.clusters(R2)) + REPS.format(rule="node_id % 4 = 0 AND node_id % 8 <> 0"))
def delete_sites(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return level2(ix.delete_sites(quarter_index(w), w.sites().where("site_id % 8 = 0")))


def early_index(w: fx.World) -> ix.Index:
    return fx.once(w.spark, w.sf_dir, f"index-early-{w.name}", lambda: ix.build_index(w.points().where("path_id % 100 < 20"), w.sites(), w.dist(), w.trips()))


PATH_ROWS = "SELECT DISTINCT m.cluster_id, p.path_id, d.metres FROM points p JOIN member m USING (node_id) JOIN detour d ON d.path_id = p.path_id AND d.site_id = m.cluster_id"


@query(base(sql.TRIPS, sql.clusters(R2), sql.DAY_POINTS, sql.detour()) + PATH_ROWS)
def add_paths(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    later = ix.add_paths(early_index(w), w.points().where("path_id % 100 >= 20"), w.dist())
    return later.path.where("level = 2").select("cluster_id", "path_id", "metres")


@query(base(sql.TRIPS, sql.clusters(R2), sql.DAY_POINTS, sql.detour()) + PATH_ROWS + " WHERE p.path_id % 100 < 10")
def delete_paths(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    kept = ix.delete_paths(w.index(), w.points().where("path_id % 100 >= 10").select("path_id").distinct())
    return kept.path.where("level = 2").select("cluster_id", "path_id", "metres")


@query(ps.statement(ps.DAYS, *ps.all_levels(), ps.stats("path_id % 100 >= 5")))
def update_batch(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    batch = ix.UpdateBatch(new_sites=w.sites().where("site_id % 6 = 1"), old_sites=w.sites().where("site_id % 8 = 0"), new_points=w.points().where("path_id % 100 >= 20"), old_paths=w.points().where("path_id % 100 < 5").select("path_id").distinct())
    return ix.index_stats(ix.apply_updates(early_index(w), batch, w.dist()))


NEW_NODE = 100


@query(ps.statement((sql.lattice(100), sql.DIST, sql.TRIPS), *(ps.members(p, r) for p, r in enumerate(ps.level_radii())),
    "road AS (SELECT (SELECT metres FROM edges WHERE src = 0 AND dst = 1) AS m, (SELECT metres FROM edges WHERE src = 1 AND dst = 0) AS b)",
    "legs AS MATERIALIZED (SELECT 0 AS nb, CAST(58 AS BIGINT) AS come, CAST(round(b * 58 / m) AS BIGINT) AS go FROM road UNION ALL SELECT 1, b - CAST(round(b * 58 / m) AS BIGINT), m - 58 FROM road)",
    "far AS MATERIALIZED (SELECT d.dst AS node, min(l.go + d.metres) AS away FROM legs l JOIN dist d ON d.src = l.nb GROUP BY ALL)",
    "home AS MATERIALIZED (SELECT d.src AS node, min(d.metres + l.come) AS back FROM legs l JOIN dist d ON d.dst = l.nb GROUP BY ALL)",
    "trip AS MATERIALIZED (SELECT node, away + back AS metres FROM far JOIN home USING (node))",
    " UNION ALL ".join(f"""SELECT CAST({p} AS INTEGER) AS level, CASE WHEN g.m <= {2 * r} THEN g.c ELSE {NEW_NODE} END AS cluster_id, CASE WHEN g.m <= {2 * r} THEN (SELECT metres FROM trip WHERE node = g.c) ELSE 0 END AS metres
  FROM (SELECT arg_min(cluster_id, struct_pack(m := t.metres + s.metres, c := cluster_id)) AS c, min(t.metres + s.metres) AS m FROM member{p} s JOIN trip t ON t.node = s.node_id WHERE s.node_id IN (0, 1)) g""" for p, r in enumerate(ps.level_radii()))))
def add_site_at_new_node(spark, sf_dir):
    """A site in mid-road: per level the cluster that it joins or leads, and its round trip to the centre."""
    w = fx.net100(spark, sf_dir)
    net = nw.split_edge(w.net(), 0, 1, 58, NEW_NODE)
    trips = round_trip(network_distances(net.edges, net.nodes))
    grown = ix.add_node_site(w.index(), NEW_NODE, trips, [0, 1])
    return grown.member.where(F.col("node_id") == NEW_NODE).select("level", "cluster_id", "metres")
