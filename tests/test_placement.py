"""Worked examples and properties of the placement methods."""

import random

import pytest
from pyspark.sql import functions as F

from waysite import fixtures as fx
from waysite import measures as ms
from waysite.functions import preference as pref
from waysite.operators import clusters as cl
from waysite.operators import detours as dt
from waysite.operators import exact as ex
from waysite.operators import greedy as gr
from waysite.operators import index as ix
from waysite.operators import network as nw
from waysite.operators import sketch as sk
from waysite.operators.distance import frontier_distances, heap_distances, round_trip
from waysite.plans.planner import choose_strategy

COVER = "path_id long, site_id long, score long"


def cover_of(spark, rows):
    return spark.createDataFrame([(p, s, v) for (p, s), v in rows.items()], COVER)


def random_cover(seed, paths=30, sites=8, binary=True):
    r = random.Random(seed)
    return {(p, s): 1_000_000 if binary else r.randrange(1, 1_000_000) for p in range(paths) for s in range(sites) if r.random() < 0.25}


def test_scores_example(spark):
    """Greedy takes site 2 and then site 1 for 0.90; the optimum is sites 1 and 3 for 1.00."""
    scores = {(1, 1): 400_000, (1, 2): 110_000, (2, 2): 500_000, (2, 3): 600_000}
    cover = cover_of(spark, scores)
    p = gr.greedy_place(cover, gr.PlacementSpec(k=2), 2)
    assert [(s[1], s[2]) for s in p.steps] == [(2, 610_000), (1, 290_000)]
    best = ex.optimal_placement(cover, cover.select("site_id").distinct(), 2, 2)
    assert sorted(best.sites) == [1, 3] and best.utility == 1_000_000
    assert ms.optimality_ratio(p.utility, best.utility) == pytest.approx(0.9) and 0.9 >= ms.guarantee("greedy", k=2, n=3)


def test_index_example(spark):
    """Four clusters, R = 1000 m, eps = 0.5: estimates and covers at 4R and 5.75R."""
    i, j, k, l = 1, 2, 3, 4
    both = lambda rows: [(0, a, b, m) for a, b, m in rows] + [(0, b, a, m) for a, b, m in rows]
    link = spark.createDataFrame(both([(i, j, 5500), (i, k, 2001), (i, l, 4000)]), "level int, cluster_id long, nbr_id long, metres long")
    member = spark.createDataFrame([(0, i, 10, 0), (0, j, 20, 0), (0, k, 30, 2000), (0, l, 40, 1000)], "level int, cluster_id long, node_id long, metres long")
    path = spark.createDataFrame([(0, j, 1, 0), (0, i, 2, 0), (0, k, 2, 2000), (0, i, 3, 2000)], "level int, cluster_id long, path_id long, metres long")
    sites = spark.createDataFrame([(10,), (30,), (40,)], "site_id long")
    index = ix.Index(ix.level_plan(4000, 4000, 0.5), 0.5, member, link, path, sites)
    found = {(r["path_id"], r["site_id"]): r["metres"] for r in ix.estimated_detours(index, 0).collect()}
    assert found == {(1, 10): 5500, (2, 10): 0, (2, 30): 4000, (2, 40): 5000, (3, 10): 2000, (3, 30): 6001, (3, 40): 7000}
    covers = lambda tau: {(r["site_id"], r["path_id"]) for r in ix.estimated_cover(index, 0, pref.binary(tau)).collect()}
    assert covers(4000) == {(10, 2), (10, 3), (30, 2)}
    assert covers(5750) == {(10, 1), (10, 2), (10, 3), (30, 2), (40, 2)}
    assert index.clusters().where("cluster_id = 2").first()["rep"] is None


def test_budget_trap(spark):
    """The ratio picks the small site and drops the large one; the safeguard takes the large one alone."""
    scores = {(p, 1): 1_000_000 for p in range(2)} | {(p, 2): 1_000_000 for p in range(10, 25)}
    sites = spark.createDataFrame([(1, 1.0), (2, 10.0)], "site_id long, cost double")
    spec = dict(k=None, budget=10.0)
    assert gr.greedy_place(cover_of(spark, scores), gr.PlacementSpec(**spec, safeguard=False), 17, sites).utility == 2_000_000
    assert gr.greedy_place(cover_of(spark, scores), gr.PlacementSpec(**spec), 17, sites).utility == 15_000_000


def test_capacity_example(spark):
    scores = {(p, 1): 1_000_000 for p in (1, 2, 3, 4)} | {(p, 2): 1_000_000 for p in (3, 4, 5)}
    sites = spark.createDataFrame([(1, 2), (2, None)], "site_id long, capacity long")
    p = gr.greedy_place(cover_of(spark, scores), gr.PlacementSpec(k=2, capacity=True), 5, sites)
    assert [(s[1], s[2]) for s in p.steps] == [(2, 3_000_000), (1, 2_000_000)]


@pytest.mark.parametrize("seed", [1, 2])
def test_greedy_modes_and_bounds(spark, seed):
    scores = random_cover(seed, binary=seed == 1)
    cover, ids = cover_of(spark, scores), list(range(8))
    runs = [gr.greedy_place(cover, gr.PlacementSpec(k=4, mode=m), 30) for m in ("recompute", "delta", "lazy")]
    assert runs[0].steps == runs[1].steps == runs[2].steps
    gains = [s[2] for s in runs[0].steps]
    assert gains == sorted(gains, reverse=True)
    best, _ = ex.brute_force(scores, ids, 4)
    assert runs[0].utility >= ms.guarantee("greedy", k=4, n=8) * best
    exact = ex.optimal_placement(cover, cover.select("site_id").distinct(), 4, 30)
    assert exact.utility == best
    assert exact.utility == ex.optimal_placement(cover, cover.select("site_id").distinct(), 4, 30, "enumerate").utility
    unit = gr.greedy_place(cover, gr.PlacementSpec(k=None, budget=4.0), 30)
    assert unit.steps == runs[0].steps


def test_stop_rules(spark):
    cover = cover_of(spark, {(1, 1): 1_000_000})
    sites = spark.createDataFrame([(1,), (2,), (3,)], "site_id long")
    p = gr.greedy_place(cover, gr.PlacementSpec(k=5), 2, sites)
    assert p.sites == [1, 3, 2] and [s[2] for s in p.steps] == [1_000_000, 0, 0]
    quota = gr.greedy_place(cover, gr.PlacementSpec(k=None, quota=1.0), 2, sites)
    assert not quota.reached and quota.sites == [1]
    assert gr.greedy_place(cover.limit(0), gr.PlacementSpec(k=2), 0).steps == []
    with pytest.raises(ValueError):
        gr.PlacementSpec(k=None)


def test_distances_agree(spark):
    net = nw.build_network(nw.id_range(spark, 16), 16)
    a, b = (sorted(map(tuple, d.collect())) for d in (heap_distances(net.edges, net.nodes, 450), frontier_distances(net.edges, net.nodes, 450)))
    assert a == b and all(m <= 450 for _, _, m in a)


def test_network_anchor(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    n, total, top = w.dist().agg(F.count("*"), F.sum("metres"), F.max("metres")).first()
    assert (n, total, top) == (10_000, 7_649_028, 2_021)
    low, high = ix.tau_limits(w.trips(), w.sites())
    assert (low, high) == (210, 4_034)
    sizes = [r["n_clusters"] for r in ix.index_stats(w.index()).orderBy("level").collect()]
    assert sizes == [100, 100, 33, 14, 5, 5]


def test_far_rejoin_needs_the_long_horizon(spark):
    """Two equal ways round from 0 to 2: the site on the one that is not taken costs nothing, yet lies far off."""
    ring = [(0, 1, 100), (1, 2, 100), (0, 3, 100), (3, 2, 100), (2, 0, 500)]
    edges = spark.createDataFrame(ring, "src long, dst long, metres int")
    nodes = spark.createDataFrame([(i,) for i in range(4)], "node_id long")
    points = spark.createDataFrame([(7, 0, 0), (7, 1, 2)], "path_id long, seq int, node_id long")
    sites = spark.createDataFrame([(3,)], "site_id long")
    whole = heap_distances(edges, nodes, None)
    assert dt.detours(points, sites, whole).first()["metres"] == 0
    assert dt.detours(points, sites, heap_distances(edges, nodes, 50)).count() == 0
    covered = dt.cover_at_query(edges, points, sites, 50, pref.binary(50))
    assert covered.count() == 1


def test_detour_rules_order(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    frames = {p: {(r["path_id"], r["site_id"]): r["metres"] for r in dt.detours(w.points(), w.sites().where("site_id < 10"), w.dist(), p).collect()} for p in dt.PAIRS}
    kernel = {(r["path_id"], r["site_id"]): r["metres"] for r in dt.kernel_detours(w.points(), w.sites().where("site_id < 10"), w.dist()).collect()}
    assert kernel == frames["any"]
    for key, any_ in frames["any"].items():
        assert 0 <= any_ <= frames["forward"][key] <= frames["same"][key]
        assert frames["forward_along"][key] <= frames["forward"][key]


def test_degenerate_paths(spark):
    edges = spark.createDataFrame([(0, 1, 100), (1, 0, 100)], "src long, dst long, metres int")
    nodes = spark.createDataFrame([(0,), (1,), (2,)], "node_id long")
    points = spark.createDataFrame([(1, 0, 0), (2, 0, 0), (2, 1, 0), (3, 0, 2)], "path_id long, seq int, node_id long")
    dist = heap_distances(edges, nodes, None)
    found = {(r["path_id"], r["site_id"]): r["metres"] for r in dt.detours(points, spark.createDataFrame([(1,), (2,)], "site_id long"), dist).collect()}
    assert found == {(1, 1): 200, (2, 1): 200, (3, 2): 0}
    assert dt.cover(dt.detours(points, spark.createDataFrame([(2,)], "site_id long"), dist), pref.binary(0)).count() == 1


def test_clusters_agree_and_dominate(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    radius = 210 * 1.75**2 / 4
    dom = cl.dominating_sets(w.trips(), radius)
    driver, peers = (sorted(map(tuple, cl.dominating_clusters(dom, e).collect())) for e in ("driver", "peers"))
    assert driver == peers
    assert sorted(n for _, n, _ in driver) == list(range(100)) and all(m <= 2 * radius for _, _, m in driver)
    centres = {c for c, _, _ in driver}
    near = w.trips().where(F.col("a").isin(list(centres)) & F.col("b").isin(list(centres)) & (F.col("a") != F.col("b"))).agg(F.min("metres")).first()[0]
    assert near > 2 * radius


def test_levels_cover_the_range():
    levels = ix.level_plan(210, 4034, 0.75)
    assert len(levels) == 6
    for tau in (210, 367.4, 367.5, 800, 4034):
        v = ix.choose_level(levels, tau)
        assert v.tau_lo <= tau < v.tau_hi and v.tau_lo == pytest.approx(4 * v.radius)
    assert ix.choose_level(levels, 209) is None and ix.choose_level(levels, 1e6) is None
    with pytest.raises(ValueError):
        ix.level_plan(0, 10, 0.5)


def test_updates_equal_rebuild(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    whole = w.index()
    base = ix.delete_paths(whole, w.points().where("path_id % 100 >= 20").select("path_id").distinct())
    grown = ix.add_paths(base, w.points().where("path_id % 100 >= 20"), w.dist())
    rows = lambda i: sorted(map(tuple, i.path.select("level", "cluster_id", "path_id", "metres").collect()))
    assert rows(grown) == rows(whole)
    fewer = ix.delete_sites(whole, w.sites().where("site_id % 3 = 0"))
    again = ix.add_sites(fewer, w.sites().where("site_id % 3 = 0"))
    reps = lambda i: sorted(tuple(r) for r in i.clusters().collect())
    assert reps(again) == reps(whole) and reps(fewer) != reps(whole)


def test_site_at_a_new_node(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    net = nw.split_edge(w.net(), 0, 1, 58, 100)
    trips = round_trip(heap_distances(net.edges, net.nodes, None))
    grown = ix.add_node_site(w.index(), 100, trips, [0, 1])
    at = {r["level"]: r["cluster_id"] for r in grown.member.where("node_id = 100").collect()}
    assert sorted(at) == list(range(6)) and at[0] == 100 and at[5] != 100


def test_sketches():
    import numpy as np

    rng = np.random.default_rng(3)
    errors = []
    for f in (4, 64):
        words = np.zeros((1, f), np.int64)
        for c in range(f):
            a, b = sk.hash_pair(c)
            h = (a * rng.integers(1, 10**8, 5000) + b) % sk.PRIME
            words[0, c] = np.bitwise_or.reduce(np.int64(1) << np.array([int(x & -x).bit_length() - 1 for x in h]))
        errors.append(sk.error_of(float(sk.estimates(words)[0]), 5000))
        assert (sk.estimates(words | words) == sk.estimates(words)).all()
    assert errors[1] < 0.2
    assert sk.estimates(np.zeros((1, 8), np.int64))[0] == 0


def test_preferences(spark):
    for p in (pref.binary(400), pref.linear(400), pref.convex(400), pref.exponential(400), pref.inconvenience()):
        assert pref.is_non_increasing(p, spark)
    assert not pref.is_non_increasing(pref.custom(400, lambda d: d / 400), spark)


def test_planner():
    spec = gr.PlacementSpec(k=5)
    index = ix.Index(ix.level_plan(210, 4034, 0.75), 0.75, None, None, None, None)
    name = lambda tau, m=1000, **o: choose_strategy(spec, tau, True, 100, m, index, **o).name
    assert [name(100), name(800), name(9999), name(800, 10**8)] == ["greedy", "index", "arbitrary", "index_sketch"]
    assert choose_strategy(gr.PlacementSpec(k=2), 800, True, 25, 1000, exact=True).name == "exact"


def test_measures():
    assert ms.relative_loss(10, 9) == pytest.approx(0.1) and ms.speed_up(2, 1) == 2 and ms.utility_pct(500_000, 1) == 50
    assert ms.guarantee("budget") == pytest.approx(0.316, abs=1e-3)
    for kind, v in (("index", {"k": 2, "clusters": 4}), ("quota", {"n": 10}), ("sketch", {"error": 0.1, "k": 2})):
        assert ms.guarantee(kind, **v) > 0


def test_plans(spark, sf_dir):
    """Filters and columns reach the scan; joins on keys, no product of rows."""
    from waysite.sources.tables import read_table

    df = read_table(spark, sf_dir, "orders", "o_orderkey", "o_totalprice").where("o_totalprice > 100000")
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(o_totalprice), GreaterThan(o_totalprice" in plan and "o_comment" not in plan
    w = fx.net100(spark, sf_dir)
    est = ix.estimated_detours(w.index(), 2)._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(level" in est and "Cartesian" not in est


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() == 5
    assert set(e.oracle_sql()) <= set(e.queries())


def test_exact_searches_of_any_size(spark, monkeypatch):
    """Repeated paths count with their number, and above MOST_ROWS rows the same search asks Spark for its gains."""
    for seed in (3, 4):
        once = random_cover(seed, paths=8, sites=6, binary=seed == 3)
        scores = {(p + 100 * i, s): v for (p, s), v in once.items() for i in range(4)}
        cover, sites = cover_of(spark, scores), spark.createDataFrame([(s,) for s in range(7)], "site_id long")
        want = ex.brute_force(scores, list(range(7)), 2)
        monkeypatch.setattr(ex, "MOST_ROWS", 2_000_000)
        held = ex.branch_and_bound(cover, sites, 2)
        monkeypatch.setattr(ex, "MOST_ROWS", 10)
        assert ex.branch_and_bound(cover, sites, 2) == held == list(want[1])
        tried = {tuple(r["members"]): r["utility"] for r in ex.enumerate_sets(cover, sites, 2).collect()}
        assert len(tried) == 21 and max(tried.values()) == want[0] and tried[(0, 6)] == sum(v for (_, s), v in scores.items() if s == 0)
        assert ex.grouped_rows(cover).count() <= 8


def test_routes_stand_for_their_paths(spark):
    """Covers, placements, sketches, indexes and similar sites of routes are those of their paths."""
    w = fx.net100(spark, "/root/testdata/sf0.001")
    r, m = w.by_routes(), w.n_paths()
    assert r.n_paths() == m and r.points().select("path_id").distinct().count() < m
    cover, grouped = w.cover(pref.linear(400)), r.cover(pref.linear(400))
    sites = fx.with_costs(w.sites(), 0.6)
    for spec in (gr.PlacementSpec(k=4, mode="auto"), gr.PlacementSpec(k=None, quota=0.5, mode="auto"), gr.PlacementSpec(k=None, budget=3.0, mode="auto"), gr.PlacementSpec(k=4, mode="delta"), gr.PlacementSpec(k=4, existing=(55,))):
        assert gr.greedy_place(cover, spec, m, sites).steps == gr.greedy_place(grouped, spec, m, sites).steps
    binary = pref.binary(800)
    assert sk.greedy_place_sketch(w.cover(binary), 3, m, 8).steps == sk.greedy_place_sketch(r.cover(binary), 3, m, 8, members=w.route_of()).steps
    for copies in (None, 8):
        whole, by_route = (ix.index_place(x.index(), gr.PlacementSpec(k=3), binary, m, None, copies, members=n) for x, n in ((w, None), (r, w.route_of())))
        assert whole.steps == by_route.steps
    assert sorted(map(tuple, ms.index_rows(w.index()).collect())) == sorted(map(tuple, ms.index_rows(r.index()).collect()))


def test_similar_pairs_of_any_size(spark, monkeypatch):
    w = fx.net100(spark, "/root/testdata/sf0.001")
    cover, grouped = w.cover(pref.binary(240)), w.by_routes().cover(pref.binary(240))
    want = sorted(map(tuple, cl.jaccard_pairs(cover, 0.3).collect()))
    monkeypatch.setattr(cl, "MOST_COMPARED", 10)
    for most in (2_000, 10):
        monkeypatch.setattr(cl, "MOST_MATRIX_SITES", most)
        assert sorted(map(tuple, cl.similar_pairs(cover, 0.3).collect())) == sorted(map(tuple, cl.similar_pairs(grouped, 0.3).collect())) == want
    assert cl.jaccard_clusters(cover, 0.3).count() == 100


def test_networks_come_from_given_tables(spark, sf_dir, tmp_path):
    """The networks of these queries follow the tables: fewer visited or inhabited nodes make a smaller network."""
    from waysite import queries as q
    from waysite import relational as rel

    spark.read.parquet(f"{sf_dir}/events.parquet").where("cast(get_json_object(props, '$.k') as int) < 9").write.parquet(f"{tmp_path}/events.parquet")
    spark.read.parquet(f"{sf_dir}/customer.parquet").where("c_nationkey < 4").write.parquet(f"{tmp_path}/customer.parquet")
    assert q.net100_edges(spark, str(tmp_path)).count() == 24 and q.net25_edges(spark, str(tmp_path)).count() == 8
    assert q.distances_net100(spark, str(tmp_path)).count() == 81
    assert {r["src"] for r in q.distances_horizon(spark, str(tmp_path)).collect()} == set(range(9))
    assert all(r["cluster_id"] < 9 for r in q.cluster_links(spark, str(tmp_path)).collect())
    assert rel.q_cte_recursive(spark, str(tmp_path)).count() == 4


def test_scores_come_from_order_lines(spark, tmp_path):
    from waysite import queries as q

    spark.createDataFrame([(1, 1, 9.0), (1, 2, 4.0), (2, 2, 1.0)], "l_orderkey long, l_suppkey long, l_quantity double").write.parquet(f"{tmp_path}/lineitem.parquet")
    spark.createDataFrame([(1, 7), (2, 8)], "s_suppkey long, s_nationkey int").write.parquet(f"{tmp_path}/supplier.parquet")
    assert [(r["site_id"], r["gain"]) for r in q.greedy_from_scores(spark, str(tmp_path)).collect()] == [(8, 900_000), (7, 500_000)]


def test_capacities_over_routes(spark, sf_dir, monkeypatch):
    """Capacities over routes give the picks, gains and utilities of their paths, in one process and beyond it."""
    w = fx.net100(spark, sf_dir)
    r, m = w.by_routes(), w.n_paths()
    for preference, share in ((pref.binary(500), 0.02), (pref.convex(500), 0.05)):
        sites = fx.with_capacities(w.sites(), share * m)
        cover, grouped = w.cover(preference), dt.cover(r.detours(), preference)
        want = gr.greedy_place(cover, gr.PlacementSpec(k=4, capacity=True, mode="arrays"), m, sites)
        assert gr.capacity_place(grouped, w.route_of(), 4, m, sites).steps == want.steps
        assert gr.capacity_place(grouped, w.route_of(), 4, m, sites, [5, 55]).utility == gr.served_by(cover, [5, 55], sites)
    monkeypatch.setattr(gr, "MOST_MEMBERS", 10)
    assert gr.capacity_place(grouped, w.route_of(), 4, m, sites).steps == want.steps
