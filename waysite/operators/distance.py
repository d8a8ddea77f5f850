"""Shortest distances within a horizon: a relational engine for networks of any size and a heap engine for networks
whose edges fit a checked broadcast."""

from __future__ import annotations

import heapq
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from waysite.sources.tables import materialize

#: Edges of a network that is still sent to every executor. As arrays an edge takes 8 bytes and a node 16: 160 MB and
#: the nodes.
MOST_BROADCAST_EDGES = 20_000_000
#: Found distances that a task hands on at once.
ROWS_AT_ONCE = 50_000
#: Nodes that are searched from at once, with one matrix of what any of them reaches.
SOURCES_AT_ONCE = 16
#: No way, or none within the bound.
BEYOND = 1 << 29


@dataclass(frozen=True)
class Roads:
    """Edges grouped by where they start: those of ids[i] are start[i] to start[i + 1] of to (places in ids) and metres."""

    ids: np.ndarray
    start: np.ndarray
    to: np.ndarray
    metres: np.ndarray

    @staticmethod
    def of(edges: DataFrame) -> Roads:
        rows = edges.select(F.col("src").cast("long"), F.col("dst").cast("long"), F.col("metres").cast("int")).toArrow()
        src, dst, metres = (rows.column(k).to_numpy() for k in range(3))
        ids = np.unique(np.concatenate([src, dst]))
        at = np.searchsorted(ids, src).astype(np.int32)
        order = np.argsort(at, kind="stable")
        start = np.searchsorted(at[order], np.arange(len(ids) + 1))
        return Roads(ids, start, np.searchsorted(ids, dst[order]).astype(np.int32), metres[order])

    def search(self) -> Callable[[int, float, set[int] | None], tuple[np.ndarray, list[int]]]:
        """A function of a node, a bound and maybe the wanted nodes that gives (nodes, metres) within the bound; with wanted
        nodes it ends when all of them are settled. The roads are turned into lists once for all its calls."""
        start, to, metres = self.start.tolist(), self.to.tolist(), self.metres.tolist()

        def reach(source: int, bound: float, wanted: set[int] | None = None) -> tuple[np.ndarray, list[int]]:
            place = int(np.searchsorted(self.ids, source))
            if place == len(self.ids) or self.ids[place] != source:
                return np.array([source]), [0]
            best, heap, done = {place: 0}, [(0, place)], {}
            left = None if wanted is None else {int(x) for x in np.searchsorted(self.ids, sorted(wanted))}
            while heap:
                d, u = heapq.heappop(heap)
                if u in done:
                    continue
                done[u] = d
                if left is not None:
                    left.discard(u)
                    if not left:
                        break
                for e in range(start[u], start[u + 1]):
                    v, m = to[e], d + metres[e]
                    if m <= bound and m < best.get(v, 1 << 62):
                        best[v] = m
                        heapq.heappush(heap, (m, v))
            return self.ids[list(done)], list(done.values())

        return reach


class Nearby:
    """Bounded searches from some nodes at once, on arrays: first the nodes that any of them reaches, then a matrix of these
    by the nodes searched from, shortened along all roads at once until nothing changes."""

    def __init__(self, roads: Roads):
        n = len(roads.ids)
        start = np.repeat(np.arange(n, dtype=np.int32), np.diff(roads.start))
        by_end = np.argsort(roads.to, kind="stable")
        turned = np.searchsorted(roads.to[by_end], np.arange(n + 1))
        self.ids = roads.ids
        self.sides = (roads.start, roads.to, roads.metres.astype(np.int32)), (turned, start[by_end], roads.metres[by_end].astype(np.int32))
        self.least, self.local = np.full(n, BEYOND, np.int32), np.full(n, -1, np.int32)

    def reach(self, places: np.ndarray, bound: int, back: bool = False) -> tuple[np.ndarray, np.ndarray]:
        """Different places of ids -> (places reached, ascending; metres from, or back to, each of the places given, BEYOND
        where they exceed the bound)."""
        first, to, metres = self.sides[back]
        self.least[places] = 0
        found, moved = [places], places
        while len(moved):
            road, number = _roads_of(first, moved)
            end, far = to[road], np.repeat(self.least[moved], number) + metres[road]
            nearer = (far <= bound) & (far < self.least[end])
            end, far = end[nearer], far[nearer]
            np.minimum.at(self.least, end, far)
            moved = np.unique(end)
            found.append(moved)
        held = np.unique(np.concatenate(found))
        self.least[held] = BEYOND
        self.local[held] = np.arange(len(held))
        road, number = _roads_of(first, held)
        begin, end, length = np.repeat(np.arange(len(held)), number), self.local[to[road]], metres[road]
        best = np.full((len(held), len(places)), BEYOND, np.int32)
        best[self.local[places], np.arange(len(places))] = 0
        self.local[held] = -1
        inside = np.flatnonzero(end >= 0)
        inside = inside[np.argsort(end[inside], kind="stable")]
        begin, end, length = begin[inside], end[inside], length[inside]
        moved = np.zeros(len(held), bool)
        moved[np.searchsorted(held, places)] = True
        while True:
            some = np.flatnonzero(moved[begin])
            if not len(some):
                return held, best
            at = np.flatnonzero(np.r_[True, np.diff(end[some]) > 0])
            nodes = end[some][at]
            far = np.minimum.reduceat(best[begin[some]] + length[some, None], at, axis=0)
            before = best[nodes]
            nearer = (far < before) & (far <= bound)
            moved[:] = False
            moved[nodes] = nearer.any(1)
            best[nodes] = np.where(nearer, far, before)


def _roads_of(first: np.ndarray, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The places of all roads of some nodes, and how many each node has."""
    number = first[nodes + 1] - first[nodes]
    return np.repeat(first[nodes] - np.cumsum(number) + number, number) + np.arange(int(number.sum())), number


def fits_broadcast(edges: DataFrame) -> bool:
    return edges.limit(MOST_BROADCAST_EDGES + 1).count() <= MOST_BROADCAST_EDGES


def way_share(roads: Roads) -> float:
    """The part of a round trip that one of its ways is at most. A way back, turned round, is a way there, longer by no more
    than the most that a road is longer than the one against it; 1 where a road has none against it."""
    n = max(len(roads.ids), 1)
    src, dst = np.repeat(np.arange(len(roads.ids)), np.diff(roads.start)), roads.to.astype(np.int64)
    order = np.lexsort((roads.metres, src * n + dst))
    keys, first = np.unique((src * n + dst)[order], return_index=True)
    least, against = roads.metres[order][first], dst * n + src
    at = np.minimum(np.searchsorted(keys, against), max(len(keys) - 1, 0))
    if not len(keys) or (keys[at] != against).any() or (roads.metres <= 0).any():
        return 1.0
    most = float((least[at] / roads.metres).max())
    return most / (1 + most)


@dataclass(frozen=True)
class Group:
    """Nodes whose round trips among each other are wanted up to trip, and their ways to and from any node up to way."""

    nodes: np.ndarray
    trip: int
    way: int = -1


#: What a row of near_ways is: a round trip, a way from a to b, or one from b to a.
TRIP, OUT, BACK = 0, 1, 2


def near_ways(edges: DataFrame, groups: dict[int, Group]) -> DataFrame:
    """(level, a, b, metres, kind) for a in the group of the level's number; b is in the same group for a TRIP, or any node.
    Each node is on trips and ways of 0 with itself. Each is searched from once, as far as its furthest group asks. For
    edges that fits_broadcast."""
    spark = edges.sparkSession
    roads = Roads.of(edges)
    share = way_share(roads)
    member = {level: np.isin(roads.ids, g.nodes) for level, g in groups.items()}
    bound = np.full(len(roads.ids), -1, np.int64)
    for level, g in groups.items():
        bound[member[level]] = np.maximum(bound[member[level]], max(min(g.trip, int(g.trip * share) + 1), g.way))
    shared = spark.sparkContext.broadcast((roads, {level: (member[level], g.trip, g.way) for level, g in groups.items()}))

    def found(near: Nearby, held: dict, blocks: pa.RecordBatch) -> Iterator[tuple[np.ndarray, ...]]:
        for far, places in zip(blocks.column(0).to_pylist(), blocks.column(1).to_pylist(), strict=True):
            places = np.array(places, np.int64)
            to, there = near.reach(places, far)
            back, home = near.reach(places, far, back=True)
            _, i, j = np.intersect1d(to, back, assume_unique=True, return_indices=True)
            trip = there[i] + home[j]
            for kind, nodes, metres, ask in ((TRIP, to[i], trip, 1), (OUT, to, there, 2), (BACK, back, home, 2)):
                of_level = {level: (h[0], h[ask]) for level, h in held.items() if h[ask] >= 0}
                most = max((m for _, m in of_level.values()), default=-1)
                node, source = np.nonzero(metres <= most)
                length, a, b = metres[node, source], places[source], nodes[node]
                for level, (of, most) in of_level.items():
                    k = np.flatnonzero((length <= most) & of[a] & (of[b] if kind == TRIP else True))
                    yield np.full(len(k), level, np.int32), near.ids[a[k]], near.ids[b[k]], length[k].astype(np.int64), np.full(len(k), kind, np.int32)

    names = ["level", "a", "b", "metres", "kind"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        roads, held = shared.value
        near = Nearby(roads)
        for batch in batches:
            for columns in _gathered(found(near, held, batch)):
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names)

    blocks = [(far, block.tolist()) for far in np.unique(bound[bound >= 0]).tolist() for block in _blocks(np.flatnonzero(bound == far))]
    table = pa.table({"far": pa.array([f for f, _ in blocks], pa.int64()), "places": pa.array([b for _, b in blocks], pa.list_(pa.int64()))})
    # Far searches take longest; dealt out in turn, every task gets as many of them.
    tasks = max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    schema = "level int, a long, b long, metres long, kind int"
    searched = spark.createDataFrame(table).coalesce(1).repartition(2 * tasks).mapInArrow(run, schema)
    lone = [(level, np.setdiff1d(g.nodes, roads.ids), kind) for level, g in groups.items() for kind in ((TRIP, OUT, BACK) if g.way >= 0 else (TRIP,))]
    rows = [(level, int(x), int(x), 0, kind) for level, nodes, kind in lone for x in nodes.tolist()]
    return searched.unionByName(spark.createDataFrame(rows, schema)) if rows else searched


def _blocks(places: np.ndarray) -> Iterator[np.ndarray]:
    """Places of near numbers, some at once."""
    places = np.sort(places)
    for a in range(0, len(places), SOURCES_AT_ONCE):
        yield places[a : a + SOURCES_AT_ONCE]


def _gathered(parts: Iterator[tuple[np.ndarray, ...]]) -> Iterator[list[np.ndarray]]:
    """Columns of few rows joined until they have ROWS_AT_ONCE."""
    held, rows = [], 0
    for part in parts:
        held.append(part)
        rows += len(part[0])
        if rows >= ROWS_AT_ONCE:
            yield [np.concatenate(c) for c in zip(*held, strict=True)]
            held, rows = [], 0
    if rows:
        yield [np.concatenate(c) for c in zip(*held, strict=True)]


def network_distances(edges: DataFrame, sources: DataFrame, horizon: int | None = None, engine: str = "auto", broadcast_limit: int = MOST_BROADCAST_EDGES, wanted: DataFrame | None = None) -> DataFrame:
    """edges(src, dst, metres), sources(node_id) -> (src, dst, metres): directed shortest distances from each source up
    to horizon (None: all). A pair without a row is out of reach. wanted(src, dst): only these pairs; its starts are
    the sources then."""
    if wanted is not None:
        wanted = wanted.select("src", "dst").distinct()
        sources = wanted.select(F.col("src").alias("node_id")).distinct()
    if engine == "auto":
        engine = "broadcast" if edges.limit(broadcast_limit + 1).count() <= broadcast_limit else "relational"
    if engine == "broadcast":
        return heap_distances(edges, sources, horizon, wanted)
    if engine == "relational":
        found = frontier_distances(edges, sources, horizon)
        return found if wanted is None else found.join(wanted.select(F.col("src").alias("s"), F.col("dst").alias("d")), (F.col("src") == F.col("s")) & (F.col("dst") == F.col("d")), "left_semi")
    raise ValueError(f"unknown engine {engine}")


def heap_distances(edges: DataFrame, sources: DataFrame, horizon: int | None, wanted: DataFrame | None = None) -> DataFrame:
    """A heap search from every source, spread over the sources; the edges are broadcast (their number is checked)."""
    shared = edges.sparkSession.sparkContext.broadcast(Roads.of(edges))
    bound, picky = float("inf") if horizon is None else horizon, wanted is not None

    def search(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        reach = shared.value.search()
        for frame in frames:
            src, dst, metres, held = [], [], [], 0
            for row in frame.itertuples(index=False):
                goals = set(map(int, row.goals)) if picky else None
                nodes, far = reach(int(row.node_id), bound, goals)
                far = np.array(far, np.int64)
                if picky:
                    kept = np.isin(nodes, list(goals))
                    nodes, far = nodes[kept], far[kept]
                src.append(np.full(len(nodes), row.node_id))
                dst.append(nodes)
                metres.append(far)
                held += len(nodes)
                if held >= ROWS_AT_ONCE:
                    yield pd.DataFrame({"src": np.concatenate(src), "dst": np.concatenate(dst), "metres": np.concatenate(metres)})
                    src, dst, metres, held = [], [], [], 0
            if src:
                yield pd.DataFrame({"src": np.concatenate(src), "dst": np.concatenate(dst), "metres": np.concatenate(metres)})

    starts = sources.select(F.col("node_id").cast("long").alias("node_id"))
    if wanted is not None:  # at most all nodes of the network a start
        starts = wanted.groupBy(F.col("src").cast("long").alias("node_id")).agg(F.collect_set("dst").alias("goals"))
    # Starts are few bytes and long searches: left to their size they would all be searched from in one task.
    spark = edges.sparkSession
    tasks = max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    return starts.repartition(tasks).mapInPandas(search, "src long, dst long, metres long")


def frontier_distances(edges: DataFrame, sources: DataFrame, horizon: int | None, most_rounds: int = 10_000) -> DataFrame:
    """Rounds of relaxation: only pairs that improved in a round are extended in the next. State is written every round."""
    best = materialize(sources.select(F.col("node_id").cast("long").alias("src"), F.col("node_id").cast("long").alias("dst"), F.lit(0).cast("long").alias("metres")), "reach")
    frontier = best
    roads = edges.select(F.col("src").alias("e_src"), F.col("dst").alias("e_dst"), F.col("metres").alias("e_metres"))
    for _ in range(most_rounds):
        step = frontier.join(roads, F.col("dst") == F.col("e_src")).select("src", F.col("e_dst").alias("dst"), (F.col("metres") + F.col("e_metres")).alias("metres"))
        if horizon is not None:
            step = step.where(F.col("metres") <= horizon)
        step = step.groupBy("src", "dst").agg(F.min("metres").alias("metres"))
        known = best.select(F.col("src").alias("k_src"), F.col("dst").alias("k_dst"), F.col("metres").alias("known"))
        better = step.join(known, (F.col("src") == F.col("k_src")) & (F.col("dst") == F.col("k_dst")), "left").where(F.col("known").isNull() | (F.col("metres") < F.col("known"))).select("src", "dst", "metres")
        frontier = materialize(better, "frontier")
        if frontier.isEmpty():
            return best
        best = materialize(best.unionByName(frontier).groupBy("src", "dst").agg(F.min("metres").alias("metres")), "reach")
    raise RuntimeError("distances did not settle")


def reverse(edges: DataFrame) -> DataFrame:
    """Roads turned round: distances on them lead to a source instead of from it."""
    return edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "metres")


def round_trip(dist: DataFrame) -> DataFrame:
    """(src, dst, metres) -> (a, b, metres): there and back; symmetric."""
    back = dist.select(F.col("src").alias("b_src"), F.col("dst").alias("b_dst"), F.col("metres").alias("b_metres"))
    return dist.join(back, (F.col("src") == F.col("b_dst")) & (F.col("dst") == F.col("b_src"))).select(F.col("src").alias("a"), F.col("dst").alias("b"), (F.col("metres") + F.col("b_metres")).alias("metres"))


def search_horizon(tau: int, points: DataFrame, dist: DataFrame, pair: str = "any") -> int:
    """How far searches must go so that no detour up to tau is missed: tau for pair="same"; else tau plus the greatest
    distance between two nodes of one path, as leaving and rejoining shortens the detour by that distance."""
    if pair == "same":
        return tau
    nodes = points.select("path_id", "node_id").distinct()
    pairs = nodes.join(nodes.select("path_id", F.col("node_id").alias("to")), "path_id")
    far = pairs.join(dist, (F.col("node_id") == F.col("src")) & (F.col("to") == F.col("dst"))).agg(F.max("metres")).first()[0]
    return tau + int(far or 0)
