"""Covers of bits against covers of pairs."""

from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F

from waysite import fixtures as fx
from waysite import workloads as wl
from waysite.functions import preference as pref
from waysite.operators import detours as dt
from waysite.operators import distance as ds
from waysite.operators import greedy as gr
from waysite.operators import index as ix
from waysite.operators import packed as pk
from waysite.operators import sketch as sk
from waysite.sources.tables import shared_dir


@pytest.fixture(scope="module")
def world(spark, sf_dir):
    return fx.net100(spark, sf_dir)


def pairs(rows, ids):
    return {(r["path_id"], int(i)) for r in rows.collect() for i in ids[np.flatnonzero(np.unpackbits(np.frombuffer(r["bits"], np.uint8))[: len(ids)])]}


def plain(cover):
    return {(r["path_id"], r["site_id"]) for r in cover.select("path_id", "site_id").collect()}


def test_packed_cover(world):
    """Pairs, weights, picks, utilities and sketches are those of the cover of pairs."""
    held, cover = world.packed_cover(400, 1200), world.cover(pref.binary(400))
    assert pairs(held.rows, held.ids) == plain(cover) and held.n_rows() == cover.count()
    m = world.n_paths()
    for k in (1, 5, 13):
        placed = gr.greedy_place(cover, gr.PlacementSpec(k=k, mode="arrays"), m)
        assert held.place(k, m).steps == placed.steps
        assert held.utilities(placed.sites) == gr.prefix_utilities(cover, placed.sites)
        assert held.place_sketch(k, m).steps == sk.greedy_place_sketch(cover, k, m, 30).steps
    fewer, some = held.of_sites(held.ids % 4 == 0), held.of_paths("path_id % 2 = 0")
    assert fewer.place(5, m).steps == gr.greedy_place(cover.where("site_id % 4 = 0"), gr.PlacementSpec(k=5, mode="arrays"), m).steps
    assert fewer.n_rows() == cover.where("site_id % 4 = 0").count() and some.n_rows() == cover.where("path_id % 2 = 0").count()
    assert some.place(5, m).steps == gr.greedy_place(cover.where("path_id % 2 = 0"), gr.PlacementSpec(k=5, mode="arrays"), m).steps


def test_packed_estimates(world, monkeypatch):
    monkeypatch.setattr(pk, "BITS_AT_ONCE", 700)
    monkeypatch.setattr(pk, "MET_AT_ONCE", 40)
    index = ix.build_index_bounded(world.points(), world.sites().where("site_id % 3 = 0"), world.net().edges, world.net().nodes, (210, 1200))
    for tau in (240, 400, 800):
        level = ix.choose_level(index.levels, tau).level
        held = pk.estimated_cover(index, level, tau)
        assert pairs(held.rows, held.ids) == plain(ix.estimated_cover(index, level, pref.binary(tau)))


def test_packed_cover_of_odd_networks(spark):
    """One-way roads, nodes without any road, and a path's node that the network doesn't have; wide distances as well."""
    for far in (1, 400):
        edges = spark.createDataFrame([(0, 1, 50 * far), (1, 2, 70 * far), (2, 0, 90 * far), (2, 5, 30 * far), (5, 9, 20 * far)], "src long, dst long, metres int")
        nodes = spark.createDataFrame([(i,) for i in (0, 1, 2, 5, 9, 700)], "node_id long")
        points = spark.createDataFrame([(1, 0, 0), (1, 1, 5), (2, 0, 700), (3, 0, -1), (3, 1, 2), (4, 0, 9)], "path_id long, seq int, node_id long")
        dist = dt.network_distances(edges, nodes)
        for tau in (0, 100 * far, 250 * far):
            held = pk.near_cover(points, spark.sparkContext.broadcast(pk.Ways.of(edges, nodes, 250 * far)), tau)
            assert pairs(held.rows, held.ids) == plain(dt.cover(dt.detours(points, nodes.select(F.col("node_id").alias("site_id")), dist), pref.binary(tau)))


def test_supplier_network_is_covered_by_bits(spark, sf_dir, monkeypatch):
    """The workloads on the supplier network never make all its detours as pairs."""
    monkeypatch.setattr(fx.World, "detours", lambda *_: pytest.fail("all detours were made"))
    assert wl.w6_time(spark, sf_dir).count() == 40 and wl.w11_time(spark, sf_dir).count() == 12


def test_loops_of_one_threshold_are_one(spark, sf_dir, monkeypatch):
    """w6_time runs a loop and makes sketches once a threshold and cover, not once a number of sites; no cover stays."""
    folder = Path(shared_dir(spark).removeprefix("file:"))
    before = set(folder.glob("packed-*"))
    calls, place, words = [], pk.PackedCover.place, pk.PackedCover.sketch_words
    monkeypatch.setattr(pk.PackedCover, "place", lambda self, k, *rest: calls.append(("place", k)) or place(self, k, *rest))
    monkeypatch.setattr(pk.PackedCover, "sketch_words", lambda self, f: calls.append(("words", f)) or words(self, f))
    rows = wl.w6_time(spark, sf_dir).collect()
    assert set(folder.glob("packed-*")) == before
    assert sorted(calls) == sorted([("place", 5)] * 6 + [("place", 25)] * 2 + [("words", 30)] * 8)
    assert sorted({(r["tau"], r["k"]) for r in rows}) == sorted({(t, 5) for t in (240, 400, 800, 1200)} | {(800, k) for k in wl.KS})
    for method in ("greedy", "index"):
        loops = [r["loop_s"] for r in sorted(rows, key=lambda r: r["k"]) if r["tau"] == 800 and r["method"] == method]
        assert loops == sorted(loops)


def test_unions_are_estimated_together(monkeypatch):
    """Picks and tries are those of one union after the other, with few calls for many sites."""
    rng = np.random.default_rng(7)
    words = np.bitwise_or.reduce(1 << np.minimum(rng.geometric(0.5, (900, 12, 30)) - 1, 31), axis=1) | rng.integers(0, 8, (900, 1))
    ids, calls, known = rng.permutation(900), [], sk.estimates
    monkeypatch.setattr(sk, "estimates", lambda w: calls.append(len(w)) or known(w))
    for prune in (True, False):
        made = []
        for at_once in (1, 256):
            monkeypatch.setattr(sk, "UNIONS_AT_ONCE", at_once)
            calls.clear()
            made.append(sk.sketch_steps(words, ids, 9, prune))
        assert made[0] == made[1] and len(calls) < 60


def test_places_are_prefixes(world):
    """The first steps of a loop are the loop of fewer sites; sketches may be given."""
    held, m = world.packed_cover(400, 1200), world.n_paths()
    long = held.place(13, m)
    assert held.place(5, m).steps == long.steps[:5] and len(long.seconds) == 13 and long.seconds == sorted(long.seconds)
    assert held.place_sketch(5, m, 30, held.sketch_words(30)).steps == held.place_sketch(5, m).steps


def test_path_ends_by_joins(world, monkeypatch):
    """Ends of paths are alike from arrays in small pieces and from joins."""
    edges, nodes = world.net().edges, world.net().nodes
    made = []
    for most in (ix.MOST_NEAR_WAYS, 0):
        monkeypatch.setattr(ix, "MOST_NEAR_WAYS", most)
        monkeypatch.setattr(ix, "MET_AT_ONCE", 30)
        index = ix.build_index_bounded(world.points(), world.sites(), edges, nodes, (210, 1200))
        made.append(sorted(map(tuple, index.path.select("level", "cluster_id", "path_id", "metres").collect())))
    assert made[0] == made[1]


def test_searches_are_spread(world):
    """Starts that fit one partition are still searched from by several tasks."""
    starts = world.sites().select(F.col("site_id").alias("node_id")).coalesce(1)
    found = dt.network_distances(world.net().edges, starts, 300)
    assert found.rdd.getNumPartitions() >= 8


def test_near_ways(spark, monkeypatch):
    """Trips and ways of groups of nodes are those of whole distances: on roads that differ by direction, on one-way roads
    and for nodes without roads, in blocks of any size."""
    rng = np.random.default_rng(5)
    both = [(i, i + step, int(rng.integers(50, 90))) for step in (1, 7) for i in range(60)]
    turned = both + [(b, a, int(rng.integers(50, 90))) for a, b, _ in both]
    for roads in (turned, both + [(66, 0, 40), (59, 0, 30)]):
        edges = spark.createDataFrame(roads, "src long, dst long, metres int")
        groups = {2: ds.Group(np.arange(70), 300), 4: ds.Group(np.array([3, 8, 15, 16, 40, 69, 1000]), 700, 240)}
        dist = {(r["src"], r["dst"]): r["metres"] for r in ds.network_distances(edges, spark.range(70).withColumnRenamed("id", "node_id")).collect()}
        dist[1000, 1000] = 0
        want = set()
        for level, g in groups.items():
            here = set(g.nodes.tolist())
            want |= {(level, a, b, m + dist[b, a], ds.TRIP) for (a, b), m in dist.items() if {a, b} <= here and (b, a) in dist and m + dist[b, a] <= g.trip}
            want |= {(level, a, b, m, ds.OUT) for (a, b), m in dist.items() if a in here and m <= g.way} | {(level, b, a, m, ds.BACK) for (a, b), m in dist.items() if b in here and m <= g.way}
        for at_once in (1, 16):
            monkeypatch.setattr(ds, "SOURCES_AT_ONCE", at_once)
            found = list(map(tuple, ds.near_ways(edges, groups).collect()))
            assert len(found) == len(set(found)) and set(found) == want
    assert ds.way_share(ds.Roads.of(edges)) == 1 and ds.way_share(ds.Roads.of(spark.createDataFrame([(0, 1, 10), (1, 0, 30)], edges.schema))) == 0.75


def test_index_searches_from_each_node_once(world, monkeypatch):
    """A bounded index finds its links and the ways of all its levels by one search, and holds no table of all near pairs."""
    made, asked = [], []
    monkeypatch.setattr(ix, "near_ways", lambda edges, groups, f=ix.near_ways: asked.append(sorted(groups)) or f(edges, groups))
    monkeypatch.setattr(ix, "network_distances", lambda *a, f=ix.network_distances, **k: made.append(k.get("wanted")) or f(*a, **k))
    edges, nodes = world.net().edges, world.net().nodes
    rows = lambda x: [sorted(map(tuple, t.collect())) for t in (x.member, x.link, x.path)]
    index = ix.build_index_bounded(world.points(), world.sites(), edges, nodes, (210, 1200))
    assert asked == [[0], [v.level for v in index.levels]] and len(made) == 1 and made[0] is not None
    monkeypatch.setattr(ix, "fits_broadcast", lambda edges: False)
    monkeypatch.setattr(ix, "level_clusters", lambda trips, radii: None)
    monkeypatch.setattr(ix, "MOST_NEAR_WAYS", 0)
    assert rows(ix.build_index_bounded(world.points(), world.sites(), edges, nodes, (210, 1200))) == rows(index)


def test_whole_covers_are_made_once(spark, sf_dir, monkeypatch):
    """All sites and all paths are one cover: it is made, placed and valued once for both."""
    w, estimated, placed = fx.netsup(spark, sf_dir, filled=False), [], []
    monkeypatch.setattr(wl, "estimate_of", lambda *a, f=wl.estimate_of: estimated.append(a) or f(*a))
    monkeypatch.setattr(wl, "place_on", lambda *a, f=wl.place_on: placed.append(a) or f(*a))
    rows = [tuple(r) for r in wl.w11_scale(spark, sf_dir).collect()]
    assert len(estimated) == 3 and len(placed) == 10 and len(rows) == 12
    whole = [r[2:] for r in rows if r[1] == 1]
    assert whole[:2] == whole[2:] and whole[0][1] == wl.size_of(wl.near_of(w, wl.TAU))
