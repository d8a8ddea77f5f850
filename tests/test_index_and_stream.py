"""Index queries with constraints, bounded builds, streamed updates across restarts, and the greedy's engines."""

import pytest
from pyspark.sql import functions as F

from waysite import fixtures as fx
from waysite.functions import preference as pref
from waysite.operators import clusters as cl
from waysite.operators import detours as dt
from waysite.operators import greedy as gr
from waysite.operators import index as ix
from waysite.operators import network as nw
from waysite.operators import paths as pt
from waysite.operators.distance import heap_distances, network_distances
from waysite.sources.tables import fresh_path, read_table
from waysite.streaming import live


@pytest.fixture(scope="module")
def world(spark, sf_dir):
    return fx.net100(spark, sf_dir)


def path_rows(index):
    return sorted(map(tuple, index.path.select("level", "cluster_id", "path_id", "metres").collect()))


def event_files(spark, events, cuts):
    """A folder with one more file for each condition, written when asked."""
    folder = fresh_path(spark, "event-parts")
    rows = events.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value", "props")
    for where in cuts:
        rows.where(where).coalesce(1).write.mode("append").parquet(folder)
        yield folder


def test_streamed_updates_lose_nothing(spark, sf_dir, world):
    """Trips cut by batches, in any order of time, and a restart between two runs: the same index as a rebuild."""
    empty = ix.delete_paths(world.index(), world.points().select("path_id").distinct())
    events, at = read_table(spark, sf_dir, "events"), fresh_path(spark, "restart")
    for folder in event_files(spark, events, ("event_id % 3 = 2", "event_id % 3 = 0", "event_id % 3 = 1")):
        grown = live.update_index(live.event_stream(spark, folder), empty, world.dist(), pt.trips_by_day, pt.day_trip(), checkpoint=at)
    assert path_rows(grown) == path_rows(world.index())
    again = live.update_index(live.event_stream(spark, folder), empty, world.dist(), pt.trips_by_day, pt.day_trip(), checkpoint=at)
    assert path_rows(again) == path_rows(grown)
    last = events.agg(F.max("ts")).first()[0]
    recent = live.update_index(live.event_stream(spark, folder), empty, world.dist(), pt.trips_by_day, pt.day_trip(), checkpoint=at, horizon_days=5)
    kept = {r["path_id"] for r in pt.event_visits(events).groupBy(pt.day_trip().alias("path_id")).agg(F.max("ts").alias("seen")).where(F.col("seen") > F.lit(last) - F.expr("INTERVAL 5 DAYS")).collect()}
    assert {r["path_id"] for r in recent.path.select("path_id").distinct().collect()} == kept


def test_streamed_updates_of_known_paths(spark, sf_dir, world):
    """An index that has the first half of each trip already: with their visits as history nothing is lost."""
    events = read_table(spark, sf_dir, "events")
    half = pt.trips_by_day(events.where("event_id % 2 = 0"))
    index = ix.build_index(half, world.sites(), world.dist(), world.trips())
    (folder,) = event_files(spark, events, ("event_id % 2 = 1",))
    rows = events.where("event_id % 2 = 0").withColumn("ts", F.col("ts").cast("timestamp")).withColumn("node_id", F.get_json_object("props", "$.k").cast("long"))
    grown = live.update_index(live.event_stream(spark, folder), index, world.dist(), pt.trips_by_day, pt.day_trip(), history=rows)
    assert path_rows(grown) == path_rows(world.index())


def test_existing_sites_count_on_the_index(world):
    """Sites that lead no cluster still serve; their estimated utility is a lower bound of the true one, and not 0."""
    reps = {r["rep"] for r in world.index().clusters().where("level = 3").collect()}
    existing = tuple(s for s in (1, 38, 77, 12) if s not in reps)
    assert existing
    p = ix.index_place(world.index(), gr.PlacementSpec(k=3, existing=existing), pref.binary(1200), world.n_paths())
    true = gr.utility_of(world.cover(pref.binary(1200)), list(existing))
    assert 0 < p.base <= true and p.utility > p.base and not set(p.sites) & set(existing)


def test_thresholds_outside_the_index(world):
    index, sites = world.index(), fx.with_capacities(world.sites(), 5)
    above = pref.binary(9000)
    cover = world.cover(above)
    assert ix.index_place(index, gr.PlacementSpec(k=3), above, world.n_paths(), cover).sites == [0, 1, 2]
    held = ix.index_place(index, gr.PlacementSpec(k=4, capacity=True), above, world.n_paths(), cover, None, sites)
    rooms = sorted((r["capacity"] for r in sites.collect()), reverse=True)[:4]
    assert held.utility == sum(rooms) * 1_000_000
    assert len(ix.index_place(index, gr.PlacementSpec(k=None, budget=2.5), above, world.n_paths(), cover, None, fx.with_costs(world.sites(), 0.0)).steps) <= 2
    assert ix.index_place(index, gr.PlacementSpec(k=None, quota=0.5), above, world.n_paths(), cover).reached
    with pytest.raises(ValueError):
        ix.index_place(index, gr.PlacementSpec(k=3), above, world.n_paths())


@pytest.mark.parametrize("options", [{}, {"existing": (55, 3)}, {"k": None, "quota": 0.8}, {"k": None, "budget": 4.0}, {"capacity": True}, {"capacity": True, "existing": (55,)}, {"k": None, "budget": 3.0, "capacity": True}])
def test_engines_agree(world, options):
    cover = world.cover(pref.convex(500))
    sites = fx.with_capacities(fx.with_costs(world.sites(), 0.6), 0.05 * world.n_paths())
    spec = {"k": 4} | options
    frames, arrays = (gr.greedy_place(cover, gr.PlacementSpec(**spec, mode=m), world.n_paths(), sites) for m in ("recompute", "arrays"))
    assert frames.steps == arrays.steps and frames.base == arrays.base
    if gr.PlacementSpec(**spec).is_plain():
        for mode in ("delta", "lazy"):
            assert gr.greedy_place(cover, gr.PlacementSpec(**spec, mode=mode), world.n_paths(), sites).steps == arrays.steps


def test_inconvenience_needs_every_pair(spark, world):
    gr.place_inconvenience(world.detours(), 2, world.n_paths(), world.sites())
    with pytest.raises(ValueError):
        gr.place_inconvenience(world.detours().where("path_id <> 7 OR site_id <> 5").where("site_id <> 9"), 2, world.n_paths(), world.sites())


def test_bounded_index(spark, world):
    """Its clusters and links are the exact index's for the same levels; path lists hold the same pairs, with metres
    between the true detour and 2R; its estimates never fall below true detours."""
    whole = ix.build_index(world.points(), world.sites(), world.dist(), world.trips(), limits=(210, 1200))
    near = ix.build_index_bounded(world.points(), world.sites(), world.net().edges, world.net().nodes, (210, 1200))
    rows = lambda df: sorted(map(tuple, df.select(*sorted(df.columns)).collect()))
    assert rows(near.member) == rows(whole.member) and rows(near.link) == rows(whole.link)
    true = {(a, b, c): m for a, b, c, m in path_rows(whole)}
    found = {(a, b, c): m for a, b, c, m in path_rows(near)}
    assert found.keys() == true.keys()
    radius = {v.level: v.radius for v in near.levels}
    assert all(true[k] <= m <= 2 * radius[k[0]] for k, m in found.items())
    exact = {(r["path_id"], r["site_id"]): r["metres"] for r in world.detours().collect()}
    assert all(r["metres"] >= exact[r["path_id"], r["site_id"]] for r in ix.estimated_detours(near, 2).collect())


def test_own_detours_without_the_matrix(world):
    pairs = ix.through_clusters(world.points(), world.index().member).where("level = 4").select("path_id", F.col("cluster_id").alias("site_id"))
    a, b = (sorted(map(tuple, dt.own_detours(pairs, world.points(), world.dist(), kernel).select("path_id", "site_id", "metres").collect())) for kernel in (True, False))
    assert a == b and len(a) == pairs.count()


def test_nodes_off_the_network(spark, world):
    """A path's node that the network doesn't have gives no detours, in the kernel as in the joins."""
    points = spark.createDataFrame([(1, 0, 5), (1, 1, 777), (2, 0, 500), (2, 1, -3)], "path_id long, seq int, node_id long")
    a, b = (sorted(map(tuple, f(points, world.sites(), world.dist()).select("path_id", "site_id", "metres").collect())) for f in (dt.kernel_detours, dt.detours))
    assert a == b and {p for p, *_ in a} == {1}


def test_shortest_filling(spark):
    """Ways around a one-way ring; a node out of reach follows directly."""
    edges = spark.createDataFrame([(0, 1, 5), (1, 2, 5), (2, 3, 5), (3, 0, 5), (0, 4, 5), (4, 2, 5)], "src long, dst long, metres int")
    points = spark.createDataFrame([(1, 0, 0), (1, 1, 2), (1, 2, 1), (2, 0, 9), (2, 1, 0), (2, 2, 0)], "path_id long, seq int, node_id long").withColumn("ts", F.lit(None).cast("timestamp"))
    found = pt.fill_gaps(points, rule="shortest", edges=edges).orderBy("path_id", "seq").collect()
    assert [r["node_id"] for r in found if r["path_id"] == 1] == [0, 1, 2, 3, 0, 1] and [r["node_id"] for r in found if r["path_id"] == 2] == [9, 0, 0]


def test_wanted_distances(spark, world):
    wanted = spark.createDataFrame([(0, 99), (0, 1), (57, 3), (57, 57)], "src long, dst long")
    exact = {(r["src"], r["dst"]): r["metres"] for r in world.dist().collect()}
    for engine in ("broadcast", "relational"):
        found = {(r["src"], r["dst"]): r["metres"] for r in network_distances(world.net().edges, world.net().nodes, engine=engine, wanted=wanted).collect()}
        assert found == {(r["src"], r["dst"]): exact[r["src"], r["dst"]] for r in wanted.collect()}


def test_minhash_finds_similar_covers(world):
    cover = world.cover(pref.binary(240))
    exact = {(r["a"], r["b"], r["both"]) for r in cl.jaccard_pairs(cover, 0.6).collect()}
    found = {(r["a"], r["b"], r["both"]) for r in cl.minhash_pairs(cover, 0.6).collect()}
    assert found <= exact and len(found) >= 0.95 * len(exact)


def test_similar_covers_are_size_checked(world, monkeypatch):
    monkeypatch.setattr(cl, "MOST_COMPARED", 10)
    with pytest.raises(ValueError):
        cl.jaccard_pairs(world.cover(pref.binary(240)), 0.5)


def test_site_in_mid_road_with_paths(spark, world):
    """A path through the new node is listed in the cluster that the node joins."""
    net = nw.split_edge(world.net(), 0, 1, 58, 100)
    dist = heap_distances(net.edges, net.nodes, None)
    points = spark.createDataFrame([(1, 0, 0), (1, 1, 100), (1, 2, 1), (2, 0, 50)], "path_id long, seq int, node_id long")
    index = ix.build_index(points.where("node_id < 100"), world.sites(), world.dist(), world.trips())
    from waysite.operators.distance import round_trip

    grown = ix.add_node_site(index, 100, round_trip(dist), [0, 1], points, dist)
    for r in grown.member.where("node_id = 100").collect():
        assert grown.path.where((F.col("level") == r["level"]) & (F.col("cluster_id") == r["cluster_id"]) & (F.col("path_id") == 1)).count() == 1


def test_jdbc_options():
    from waysite.sources.tables import jdbc_options

    assert jdbc_options("jdbc:x", "detours", "path_id", 0, 99, 4) == {"url": "jdbc:x", "dbtable": "detours", "partitionColumn": "path_id", "lowerBound": "0", "upperBound": "99", "numPartitions": "4"}


def test_workspace(world, spark):
    """The planner's ways give what the operators give."""
    from waysite.api import Workspace

    ws = Workspace(spark, world.points(), world.sites(), world.net().edges, world.detours(), world.index())
    plain = gr.greedy_place(world.cover(pref.binary(150)), gr.PlacementSpec(k=3, mode="auto"), world.n_paths(), world.sites())
    assert ws.place_sites(150, 3).steps == plain.steps
    assert ws.place_sites(800, 3).steps == ix.index_place(world.index(), gr.PlacementSpec(k=3), pref.binary(800), world.n_paths()).steps
    assert ws.place_sites(9000, 2).sites == [0, 1]
    assert len(ws.place_sites(9000, None, budget=2.0).steps) == 2
    bare = Workspace(spark, world.points(), world.sites(), world.net().edges)
    assert sorted(map(tuple, bare.cover_of(pref.linear(300)).collect())) == sorted(map(tuple, world.cover(pref.linear(300)).select("path_id", "site_id", "metres", "score").collect()))
