"""Covers of few sites as bits: the same answers as from rows."""

import numpy as np
import pytest

from waysite import fixtures as fx
from waysite.functions import preference as pref
from waysite.operators import bits as bt
from waysite.operators import exact as ex
from waysite.operators import greedy as gr
from waysite.operators import index as ix
from waysite.operators import sketch as sk


@pytest.fixture(scope="module")
def routes(spark, sf_dir):
    paths = fx.net100(spark, sf_dir, filled=True)
    w = paths.by_routes()
    return w, paths.route_of(), w.cover(pref.binary(400))


def no_rows(*_):
    raise AssertionError("the cover was taken as rows")


def test_large_covers_are_placed_as_bits(routes, spark, monkeypatch):
    w, _, cover = routes
    specs = [gr.PlacementSpec(k=7), gr.PlacementSpec(k=4, existing=(55, 33)), gr.PlacementSpec(k=None, quota=0.6), gr.PlacementSpec(k=None, budget=5.0)]
    tables = [w.sites(), None, w.sites(), fx.with_costs(w.sites().where("site_id % 3 <> 0"), 0.8)]
    ask = lambda mode: [gr.greedy_place(cover, gr.replace(s, mode=mode), w.n_paths(), t) for s, t in zip(specs, tables, strict=True)]
    want = ask("arrays")
    monkeypatch.setattr(gr, "BIT_ROWS", 10)
    monkeypatch.setattr(gr, "MOST_ARRAY_ROWS", 10)
    monkeypatch.setattr(gr._ArrayLoop, "__init__", no_rows)
    monkeypatch.setattr(gr._FrameLoop, "__init__", no_rows)
    found = ask("auto")
    assert [(p.steps, p.base, p.reached) for p in found] == [(p.steps, p.base, p.reached) for p in want]


def test_large_covers_have_capacities_as_bits(routes, monkeypatch):
    w, members, cover = routes
    alone = cover.withColumn("score", cover["score"] / cover["times"]).drop("times")
    sites = fx.with_capacities(w.sites(), 0.02 * w.n_paths())
    ask = lambda: (gr.capacity_place(alone, members, 5, w.n_paths(), sites), gr.capacity_place(alone, members, 5, w.n_paths(), sites, [55, 3, 90]))
    want = ask()
    monkeypatch.setattr(gr, "BIT_ROWS", 10)
    monkeypatch.setattr(gr, "MOST_ARRAY_ROWS", 10)
    monkeypatch.setattr(gr._FrameLoop, "__init__", no_rows)
    assert [p.steps for p in ask()] == [p.steps for p in want]


def test_sketches_of_routes_from_bits(routes, monkeypatch):
    _, members, cover = routes
    ids, words = sk.sketch_words(cover, 40, members)
    monkeypatch.setattr(sk, "site_bits", lambda _: None)
    want = sk.sketch_words(cover, 40, members)
    assert np.array_equal(ids, want[0]) and np.array_equal(words, want[1])


def test_large_covers_are_searched_as_bits(spark, sf_dir, monkeypatch):
    """The optimum of routes, whose numbers differ, without a table of all their rows."""
    w = fx.net25(spark, sf_dir).by_routes()
    cover, sites = w.cover(pref.binary(240)), w.sites().unionByName(spark.createDataFrame([(99,)], "site_id long"))
    want = [ex.branch_and_bound(cover, sites, k) for k in (1, 3)]
    monkeypatch.setattr(ex, "BIT_ROWS", 10)
    monkeypatch.setattr(ex, "grouped_rows", no_rows)
    assert [ex.branch_and_bound(cover, sites, k) for k in (1, 3)] == want


def test_covers_that_are_no_bits(spark, monkeypatch):
    """Different scores of a path, a pair given twice, no rows, too many sites."""
    frame = lambda rows: spark.createDataFrame(rows, "path_id long, site_id long, score long")
    rows = [(p, s, 10 * p) for p in range(1, 5) for s in range(70 * p)]
    held = bt.site_bits(frame(rows))
    path, words, score = held.by_path()
    assert {int(p): (np.flatnonzero([bt.has_bit(w[None], i)[0] for i in range(280)]).tolist(), int(u)) for p, w, u in zip(path, words, score, strict=True)} == {p: (list(range(70 * p)), 10 * p) for p in range(1, 5)}
    assert bt.site_bits(frame([*rows, (1, 200, 7)])) is None and bt.site_bits(frame([*rows, rows[0]])) is None and bt.site_bits(frame([])) is None
    monkeypatch.setattr(bt, "MOST_BIT_SITES", 100)
    assert bt.site_bits(frame(rows)) is None


def test_cluster_paths_need_one_pass(spark, sf_dir, monkeypatch):
    """With the kernel the rows of paths through clusters come from their routes, not from joins of all pairs."""
    w = fx.net100(spark, sf_dir, filled=True)
    stray = spark.createDataFrame([(7, 0, 5000, None), (8, 0, 5000, None), (8, 1, 3, None), (9, 0, 3, None), (9, 1, 3, None)], w.points().schema)
    points = w.points().where("path_id % 7 = 0 AND path_id > 10").unionByName(stray)
    member = w.index().member.unionByName(spark.createDataFrame([(0, 5000, 5000, 0), (1, 5000, 5000, 0)], w.index().member.select("level", "cluster_id", "node_id", "metres").schema))
    rows = lambda kernel: sorted(map(tuple, ix.cluster_paths(points, member, w.dist(), kernel).collect()))
    want = rows(False)
    monkeypatch.setattr(ix, "through_clusters", no_rows)
    assert rows(True) == want
