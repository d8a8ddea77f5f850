"""The index of clusters at several radii: building, choosing a level, estimating detours, placing, updating."""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.core.broadcast import Broadcast
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from waysite.functions.preference import Preference
from waysite.operators.baselines import arbitrary_place
from waysite.operators.clusters import dominating_clusters, dominating_sets, level_clusters
from waysite.operators.detours import FAR, Matrix, cover, own_detours, route_arrays, times_over
from waysite.operators.distance import BACK, TRIP, Group, fits_broadcast, near_ways, network_distances, round_trip
from waysite.operators.greedy import Placement, PlacementSpec, greedy_place
from waysite.operators.sketch import greedy_place_sketch
from waysite.sources.tables import discard, fresh_path, materialize, write_partitioned


@dataclass(frozen=True)
class Level:
    level: int
    radius: float
    tau_lo: float
    tau_hi: float


@dataclass(frozen=True)
class Index:
    """Relations keyed by level. cluster: centre and representative (null without a site); member: nodes with the
    round trip to the centre; link: neighbour centres with round trips; path: paths with their detour to the centre;
    sites: the candidate sites."""

    levels: tuple[Level, ...]
    eps: float
    member: DataFrame  # level, cluster_id, node_id, metres
    link: DataFrame  # level, cluster_id, nbr_id, metres
    path: DataFrame  # level, cluster_id, path_id, metres
    sites: DataFrame  # site_id
    rule: str = "closest"
    visits: DataFrame | None = None  # node_id, n: for the busiest rule
    reps: DataFrame | None = None  # level, cluster_id, rep, rep_metres
    times: DataFrame | None = None  # path_id, times: where paths stand for several

    def clusters(self) -> DataFrame:
        return self.reps if self.reps is not None else representatives(self.member, self.sites, self.rule, self.visits)


def tau_limits(trips: DataFrame, sites: DataFrame) -> tuple[int, int]:
    """Least and largest round trip between two different sites."""
    held = sites.select("site_id")
    two = trips.where("a <> b").join(held, F.col("a") == F.col("site_id"), "left_semi").join(held, F.col("b") == F.col("site_id"), "left_semi")
    low, high = two.agg(F.min("metres"), F.max("metres")).first()
    return int(low), int(high)


def level_plan(tau_min: float, tau_max: float, eps: float) -> tuple[Level, ...]:
    """Radii from tau_min / 4 growing by (1 + eps); level p serves 4R <= tau < 4R(1 + eps). Limits by repeated
    multiplication, so no logarithm decides at an end."""
    if not 0 < tau_min <= tau_max or eps <= 0:
        raise ValueError("need 0 < tau_min <= tau_max and eps > 0")
    out, low = [], float(tau_min)
    while low <= tau_max:
        high = low * (1 + eps)
        out.append(Level(len(out), low / 4, low, high))
        low = high
    return tuple(out)


def choose_level(levels: tuple[Level, ...], tau: float) -> Level | None:
    """The level that serves tau; None below the first (use the plain greedy) or above the last."""
    return next((v for v in levels if v.tau_lo <= tau < v.tau_hi), None)


def representatives(member: DataFrame, sites: DataFrame, rule: str = "closest", visits: DataFrame | None = None) -> DataFrame:
    """(level, cluster_id, rep, rep_metres): of a cluster's sites the closest to its centre, or the busiest; ties by
    the smaller id. Clusters without a site keep a null representative: they still carry paths."""
    held = sites.select(F.col("site_id").alias("s"))
    known = member.join(held, F.col("node_id") == F.col("s"), "left")
    is_site = F.col("s").isNotNull()
    if rule == "busiest":
        known = known.join(visits.select(F.col("node_id").alias("v"), "n"), F.col("node_id") == F.col("v"), "left")
        order = F.struct((-F.coalesce("n", F.lit(0))).alias("o"), "node_id")
    elif rule == "closest":
        order = F.struct(F.col("metres").alias("o"), "node_id")
    else:
        raise ValueError(f"unknown rule {rule}")
    best = F.min(F.when(is_site, F.struct(order.alias("o"), F.col("node_id").alias("rep"), F.col("metres").alias("m")))).alias("best")
    return known.groupBy("level", "cluster_id").agg(best).select("level", "cluster_id", F.col("best.rep").alias("rep"), F.col("best.m").alias("rep_metres"))


def cluster_links(member: DataFrame, trips: DataFrame, levels: tuple[Level, ...], eps: float) -> DataFrame:
    """(level, cluster_id, nbr_id, metres): centres within a round trip of 4R(1 + eps) of each other."""
    centres = member.select("level", "cluster_id").distinct()
    limits = member.sparkSession.createDataFrame([(v.level, 4 * v.radius * (1 + eps)) for v in levels], "lv int, reach double")
    other = centres.select(F.col("level").alias("l2"), F.col("cluster_id").alias("nbr_id"))
    near = centres.join(F.broadcast(limits), F.col("level") == F.col("lv")).join(trips, F.col("cluster_id") == F.col("a")).where(F.col("metres") <= F.col("reach"))
    joined = near.join(other, (F.col("level") == F.col("l2")) & (F.col("b") == F.col("nbr_id")))
    return joined.where(F.col("cluster_id") != F.col("nbr_id")).select("level", "cluster_id", "nbr_id", "metres")


def through_clusters(points: DataFrame, member: DataFrame) -> DataFrame:
    """(level, cluster_id, path_id): the clusters that each path passes."""
    return points.select("path_id", "node_id").distinct().join(member.select("level", "cluster_id", "node_id"), "node_id").select("level", "cluster_id", "path_id").distinct()


def cluster_paths(points: DataFrame, member: DataFrame, dist: DataFrame, kernel: bool = True) -> DataFrame:
    """(level, cluster_id, path_id, metres): the paths through each cluster and their detour, as whole paths, to its
    centre. Only these pairs are computed, each once for all levels where the centre is the same; with the kernel in one pass
    over the different routes, which has a route's clusters of all levels at once."""
    if kernel:
        return kernel_cluster_paths(points, member, dist)
    through = materialize(through_clusters(points, member), "through")
    far = own_detours(through.select("path_id", F.col("cluster_id").alias("site_id")), points, dist, kernel).select(F.col("path_id").alias("p"), F.col("site_id").alias("centre"), "metres")
    return through.join(far, (F.col("path_id") == F.col("p")) & (F.col("cluster_id") == F.col("centre"))).select("level", "cluster_id", "path_id", "metres")


def kernel_cluster_paths(points: DataFrame, member: DataFrame, dist: DataFrame) -> DataFrame:
    """cluster_paths on networks of up to MOST_KERNEL_NODES nodes: matrix and members are broadcast, a route's centres are
    one numpy step, and each of its paths has their rows. A centre on the path costs nothing and needs no distance."""
    rows = member.select("level", F.col("node_id").cast("long"), F.col("cluster_id").cast("long")).toArrow()
    level_of, node_of, centre_of = (rows.column(k).to_numpy() for k in range(3))
    ids, levels = np.unique(node_of), np.unique(level_of)
    own = np.full((len(levels), len(ids)), -1, np.int64)
    own[np.searchsorted(levels, level_of), np.searchsorted(ids, node_of)] = np.searchsorted(ids, centre_of)
    shared = points.sparkSession.sparkContext.broadcast((Matrix.of(dist), ids, levels, own))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        matrix, ids, levels, own = shared.value
        reached = np.isin(ids, matrix.ids)
        names = ["level", "cluster_id", "path_id", "metres"]
        for batch in batches:
            found, number = [], 0
            for nodes, paths in zip(batch.column(0), batch.column(1), strict=True):
                nodes = nodes.values.to_numpy()
                on = np.flatnonzero(np.isin(ids, nodes))
                level, centre = np.nonzero(own[:, on] >= 0)
                level, centre = np.divmod(np.unique(level * max(len(ids), 1) + own[:, on][level, centre]), max(len(ids), 1))
                metres = np.full(len(ids), FAR, np.int64)
                goals = np.unique(centre)
                goals = goals[reached[goals]]
                metres[goals] = matrix.detours(nodes, ids[goals])
                metres[on] = 0
                kept = np.flatnonzero(metres[centre] <= FAR // 2)
                paths = paths.values.to_numpy()
                found.append((np.repeat(levels[level[kept]], len(paths)), np.repeat(ids[centre[kept]], len(paths)), np.tile(paths, len(kept)), np.repeat(metres[centre[kept]], len(paths))))
                number += len(found[-1][0])
                if number > MET_AT_ONCE:
                    yield pa.RecordBatch.from_arrays(_columns(found), names)
                    found, number = [], 0
            if found:
                yield pa.RecordBatch.from_arrays(_columns(found), names)

    # Equal routes share a row until there are many of them: then some rows of theirs follow each other.
    routes = route_arrays(points.select(F.col("path_id").cast("long").alias("path_id"), F.col("node_id").cast("long").alias("node_id")))
    alike = routes.groupBy("nodes", F.pmod("path_id", F.lit(ALIKE_ROWS)).alias("part")).agg(F.collect_list("path_id").alias("paths")).select("nodes", "paths")
    return alike.mapInArrow(run, "level int, cluster_id long, path_id long, metres long")


def _columns(parts: list[tuple[np.ndarray, ...]]) -> list[pa.Array]:
    """level, cluster_id, path_id and metres of some routes as columns."""
    return [pa.array(np.concatenate(c), kind) for c, kind in zip(zip(*parts, strict=True), (pa.int32(), pa.int64(), pa.int64(), pa.int64()), strict=True)]


def near_cluster_paths(points: DataFrame, member: DataFrame, levels: tuple[Level, ...], ways: DataFrame, edges: DataFrame) -> DataFrame:
    """As cluster_paths, with both ways between path and centre of 2R at most, as the round trip that put a path's node
    into the cluster has them. The metres may exceed the whole path's detour, never that round trip. ways(level, node, c,
    metres, home): ways up to 2R between nodes and centres; those between a path's ends are searched for as they are wanted."""
    keys = ["level", "cluster_id", "path_id"]
    if ways.count() <= MOST_NEAR_WAYS:
        held = points.sparkSession.sparkContext.broadcast(_held_ways(member, levels, ways))
        routes = materialize(points.groupBy(F.col("path_id").cast("long").alias("path_id")).agg(F.collect_set(F.col("node_id").cast("long")).alias("nodes")), "index-routes")
        gaps = materialize(gaps_between(edges, points, wanted_gaps(routes, held).distinct()), "index-gaps")
        if gaps.count() <= MOST_NEAR_WAYS:
            return least_ways(routes, held, gaps)
        ends = materialize(path_ends(routes, held), "index-ends")
    else:
        ends = materialize(joined_ends(points, member, *(ways.where("home" if side else "not home").select("level", "node", "c", "metres") for side in (False, True))), "index-ends")
        gaps = materialize(gaps_between(edges, points, ends.where("v <> w").select(F.col("v").alias("src"), F.col("w").alias("dst"))), "index-gaps")
    gaps = gaps.select(F.col("src").alias("g1"), F.col("dst").alias("g2"), F.col("metres").alias("gap"))
    known = ends.join(gaps, (F.col("v") == F.col("g1")) & (F.col("w") == F.col("g2")), "left")
    return known.where("v = w OR gap IS NOT NULL").groupBy(*keys).agg(F.min(F.col("way") - F.coalesce("gap", F.lit(0))).cast("long").alias("metres"))


def gaps_between(edges: DataFrame, points: DataFrame, wanted: DataFrame) -> DataFrame:
    return network_distances(edges, points.select("node_id"), wanted=wanted)


#: Ways between nodes and centres, or gaps in paths, that are still sent to every worker, 12 bytes each: 240 MB.
MOST_NEAR_WAYS = 20_000_000
#: Rows over which the paths of one route are spread.
ALIKE_ROWS = 64
#: Pairs of a path's clusters and nodes that a task has at once.
MET_AT_ONCE = 2_000_000


def _held_ways(member: DataFrame, levels: tuple[Level, ...], ways: DataFrame) -> tuple[np.ndarray, dict]:
    """Ids of all nodes, and by level the place of each node's centre and the ways there and home."""
    rows = member.select("level", F.col("node_id").cast("long"), F.col("cluster_id").cast("long")).toArrow()
    level_of, node_of, centre_of = (rows.column(k).to_numpy() for k in range(3))
    ids = np.unique(node_of)
    rows = ways.select("level", F.col("node").cast("long"), F.col("c").cast("long"), F.col("metres").cast("long"), "home").toArrow()
    way_level, home = rows.column(0).to_numpy(), rows.column(4).to_numpy()
    held = {}
    for v in levels:
        at, centre = level_of == v.level, np.full(len(ids), -1, np.int32)
        centre[np.searchsorted(ids, node_of[at])] = np.searchsorted(ids, centre_of[at])
        there, back = (_keyed(*(rows.column(k).to_numpy()[(way_level == v.level) & (home == side)] for k in (1, 2, 3)), ids) for side in (False, True))
        held[v.level] = centre, there, back
    return ids, held


def _met(batches: Iterator[pa.RecordBatch], shared: Broadcast) -> Iterator[tuple[np.ndarray, int, np.ndarray, tuple[np.ndarray, ...]]]:
    """(ids, level, the paths that _ends numbers, _ends) of the routes of a task."""
    ids, held = shared.value
    for batch in batches:
        paths, lists = batch.column(0).to_numpy(), batch.column(1)
        offsets = lists.offsets.to_numpy().astype(np.int64)
        nodes = lists.values.to_numpy()
        squares = np.cumsum(np.diff(offsets) ** 2)
        lo = 0
        while lo < len(paths):
            hi = max(lo + 1, int(np.searchsorted(squares, (squares[lo - 1] if lo else 0) + MET_AT_ONCE, "right")))
            path = np.repeat(np.arange(hi - lo), np.diff(offsets[lo : hi + 1]))
            for level, found in _ends(path, nodes[offsets[lo] : offsets[hi]], ids, held):
                yield ids, level, paths[lo:hi], found
            lo = hi


def path_ends(routes: DataFrame, shared: Broadcast) -> DataFrame:
    """(level, cluster_id, path_id, v, w, way): for each cluster that a path passes the nodes v and w of the path from which,
    and to which, its centre is 2R away at most, and the length of both ways."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, level, paths, (c, p, v, w, way) in _met(batches, shared):
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in (np.full(len(c), level, np.int32), ids[c], paths[p], ids[v], ids[w], way.astype(np.int64))], ["level", "cluster_id", "path_id", "v", "w", "way"])

    return routes.mapInArrow(run, "level int, cluster_id long, path_id long, v long, w long, way long")


def wanted_gaps(routes: DataFrame, shared: Broadcast) -> DataFrame:
    """(src, dst): the different ends of path_ends."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, _, _, (_, _, v, w, _) in _met(batches, shared):
            key = np.unique(v[v != w] * len(ids) + w[v != w])
            yield pa.RecordBatch.from_arrays([pa.array(ids[x]) for x in np.divmod(key, max(len(ids), 1))], ["src", "dst"])

    return routes.mapInArrow(run, "src long, dst long")


def least_ways(routes: DataFrame, shared: Broadcast, gaps: DataFrame) -> DataFrame:
    """(level, cluster_id, path_id, metres): over the ends of a path near a centre the least of both ways less the gap that
    leaving and rejoining saves. gaps(src, dst, metres): those that there are."""
    rows = gaps.select(F.col("src").cast("long"), F.col("dst").cast("long"), F.col("metres").cast("long")).toArrow()
    known = gaps.sparkSession.sparkContext.broadcast(_keyed(*(rows.column(k).to_numpy() for k in range(3)), shared.value[0]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, level, paths, (c, p, v, w, way) in _met(batches, shared):
            less = way.astype(np.int64)
            apart = np.flatnonzero(v != w)
            hit, metres = _looked_up(known.value, v[apart] * len(ids) + w[apart])
            less[apart[hit]] -= metres
            kept = v == w
            kept[apart[hit]] = True
            c, p, less = c[kept], p[kept], less[kept]
            first = np.flatnonzero(np.r_[len(c) > 0, (np.diff(c) != 0) | (np.diff(p) != 0)][: len(c)])
            if len(first):
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in (np.full(len(first), level, np.int32), ids[c[first]], paths[p[first]], np.minimum.reduceat(less, first))], ["level", "cluster_id", "path_id", "metres"])

    return routes.mapInArrow(run, "level int, cluster_id long, path_id long, metres long")


def _keyed(node: np.ndarray, centre: np.ndarray, metres: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Ways of a level as sorted numbers of (node, centre) and their metres."""
    at = np.minimum(np.searchsorted(ids, node), max(len(ids) - 1, 0))
    known = ids[at] == node if len(ids) else np.zeros(len(node), bool)
    key = at[known] * len(ids) + np.searchsorted(ids, centre[known])
    order = np.argsort(key)
    return key[order], metres[known][order].astype(np.int32)


def _looked_up(held: tuple[np.ndarray, np.ndarray], key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The places of the keys that are held, and their metres."""
    keys, metres = held
    at = np.minimum(np.searchsorted(keys, key), max(len(keys) - 1, 0))
    hit = np.flatnonzero(keys[at] == key) if len(keys) else np.zeros(0, np.int64)
    return hit, metres[at[hit]]


def _ends(path: np.ndarray, nodes: np.ndarray, ids: np.ndarray, held: dict) -> Iterator[tuple[int, tuple[np.ndarray, ...]]]:
    """path_ends of some paths, by level: places of centre, path and ends. path: ascending, that of each of the nodes."""
    at = np.minimum(np.searchsorted(ids, nodes), max(len(ids) - 1, 0))
    known = ids[at] == nodes if len(ids) else np.zeros(len(nodes), bool)
    path, at = path[known], at[known]
    for level, (centre, there, home) in held.items():
        own = centre[at].astype(np.int64)
        through = np.unique(path[own >= 0] * len(ids) + own[own >= 0])
        p, c = np.divmod(through, max(len(ids), 1))
        first = np.searchsorted(path, p)
        number = np.searchsorted(path, p, "right") - first
        t = np.repeat(np.arange(len(p)), number)
        node = at[np.repeat(first - np.cumsum(number) + number, number) + np.arange(int(number.sum()))]
        key = node * len(ids) + c[t]
        out, out_m = _looked_up(there, key)
        back, back_m = _looked_up(home, key)
        # Every leave meets every rejoin of the same path and cluster; both are in order of these.
        begin = np.searchsorted(t[back], t[out])
        meets = np.searchsorted(t[back], t[out], "right") - begin
        left = np.repeat(np.arange(len(out)), meets)
        right = np.repeat(begin - np.cumsum(meets) + meets, meets) + np.arange(int(meets.sum()))
        of = t[out[left]]
        v, w = node[out[left]], node[back[right]]
        yield level, (c[of], p[of], v, w, out_m[left] + back_m[right])


def joined_ends(points: DataFrame, member: DataFrame, there: DataFrame, home: DataFrame) -> DataFrame:
    """path_ends by joins, for any number of ways."""
    keys = ["level", "cluster_id", "path_id"]
    through = materialize(through_clusters(points, member), "through")
    nodes = points.select(F.col("path_id").alias("p"), "node_id").distinct()
    met = through.join(nodes, F.col("path_id") == F.col("p"))
    leave = met.join(there.select(F.col("level").alias("lv"), "node", "c", F.col("metres").alias("out")), (F.col("level") == F.col("lv")) & (F.col("node_id") == F.col("node")) & (F.col("cluster_id") == F.col("c"))).select(*keys, F.col("node").alias("v"), "out")
    rejoin = met.join(home.select(F.col("level").alias("lv"), "node", "c", F.col("metres").alias("home")), (F.col("level") == F.col("lv")) & (F.col("node_id") == F.col("node")) & (F.col("cluster_id") == F.col("c"))).select(*keys, F.col("node").alias("w"), "home")
    return leave.join(rejoin, keys).select(*keys, "v", "w", (F.col("out") + F.col("home")).alias("way"))


def compress_paths(points: DataFrame, member: DataFrame) -> DataFrame:
    """(level, path_id, seq, cluster_id): paths as sequences of clusters, runs of one cluster collapsed."""
    w = Window.partitionBy("level", "path_id").orderBy("seq")
    placed = points.select("path_id", "seq", "node_id").join(member.select("level", "cluster_id", "node_id"), "node_id")
    turned = placed.withColumn("last", F.lag("cluster_id").over(w)).where(F.col("last").isNull() | (F.col("last") != F.col("cluster_id")))
    return turned.select("level", "path_id", (F.row_number().over(w) - 1).alias("seq"), "cluster_id")


def build_index(points: DataFrame, sites: DataFrame, dist: DataFrame, trips: DataFrame, eps: float = 0.75, rule: str = "closest", engine: str = "auto", kernel: bool = True, limits: tuple[int, int] | None = None) -> Index:
    """All levels for the paths and sites, from stored distances; relations are written to the shared folder, partitioned
    by level."""
    levels = level_plan(*(limits or tau_limits(trips, sites)), eps)
    member = stored(clustered(trips, levels, engine), "index-member")
    path = stored(cluster_paths(points, member, dist, kernel), "index-path")
    link = stored(cluster_links(member, trips, levels, eps), "index-link")
    return with_sites(Index(levels, eps, member, link, path, sites, rule, visits_of(points, rule)), sites)


def build_index_bounded(points: DataFrame, sites: DataFrame, edges: DataFrame, nodes: DataFrame, limits: tuple[int, int], eps: float = 0.75, rule: str = "closest", engine: str = "auto") -> Index:
    """As build_index for networks whose distances can't all be held: searches go as far as a level needs, 2R for
    dominance and paths and 4R(1 + eps) between centres, whatever the size of the network. limits: the least and the
    largest threshold to be served. metres of paths are those of near_cluster_paths, so estimates stay no less than the
    true detours."""
    levels = level_plan(*limits, eps)
    fits = fits_broadcast(edges)
    most = math.floor(2 * levels[-1].radius)
    if fits:
        ids = np.unique(nodes.select(F.col("node_id").cast("long")).toArrow().column(0).to_numpy())
        near, trips = None, materialize(near_ways(edges, {0: Group(ids, most)}).select("a", "b", "metres"), "index-trips")
    else:
        near = materialize(network_distances(edges, nodes, most), "index-near")
        trips = materialize(round_trip(near).where(F.col("metres") <= most), "index-trips")
    member = stored(clustered(trips, levels, engine), "index-member")
    if fits:
        rows = member.select("level", F.col("cluster_id").cast("long")).distinct().toArrow()
        level_of, centre = rows.column(0).to_numpy(), rows.column(1).to_numpy()
        groups = {v.level: Group(centre[level_of == v.level], math.floor(4 * v.radius * (1 + eps)), math.floor(2 * v.radius)) for v in levels}
        found = materialize(near_ways(edges, groups), "index-found")
        links = found.where((F.col("kind") == TRIP) & (F.col("a") != F.col("b"))).select("level", F.col("a").alias("cluster_id"), F.col("b").alias("nbr_id"), "metres")
        ways = found.where(F.col("kind") != TRIP).select("level", F.col("b").alias("node"), F.col("a").alias("c"), "metres", (F.col("kind") != BACK).alias("home"))
    else:
        links, ways = joined_links(member, edges, levels, eps), materialize(joined_ways(member, levels, near), "index-ways")
    link = stored(links, "index-link")
    path = stored(near_cluster_paths(points, member, levels, ways, edges), "index-path")
    return with_sites(Index(levels, eps, member, link, path, sites, rule, visits_of(points, rule)), sites)


def joined_links(member: DataFrame, edges: DataFrame, levels: tuple[Level, ...], eps: float) -> DataFrame:
    """As cluster_links, by searches from the centres as far as their levels go; for any number of edges."""
    links = None
    for v in levels:
        reach = math.floor(4 * v.radius * (1 + eps))
        centres = member.where(F.col("level") == v.level).select(F.col("cluster_id").alias("node_id")).distinct()
        ways = network_distances(edges, centres, reach).join(centres.select(F.col("node_id").alias("c")), F.col("dst") == F.col("c"), "left_semi")
        one = round_trip(materialize(ways, "index-ways")).where((F.col("a") != F.col("b")) & (F.col("metres") <= reach)).select(F.lit(v.level).alias("level"), F.col("a").alias("cluster_id"), F.col("b").alias("nbr_id"), "metres")
        links = one if links is None else links.unionByName(one)
    return links


def joined_ways(member: DataFrame, levels: tuple[Level, ...], near: DataFrame) -> DataFrame:
    """(level, node, c, metres, home): ways of 2R at most from nodes to centres, or home from there. near(src, dst, metres):
    distances up to 2R of the highest level."""
    plan = member.sparkSession.createDataFrame([(v.level, 2 * v.radius) for v in levels], "lv int, reach double")
    centres = member.select("level", "cluster_id").distinct().join(F.broadcast(plan), F.col("level") == F.col("lv")).select("level", F.col("cluster_id").alias("c"), "reach")
    there = near.join(centres, F.col("dst") == F.col("c")).where("metres <= reach").select("level", F.col("src").alias("node"), "c", "metres", F.lit(False).alias("home"))
    home = near.join(centres, F.col("src") == F.col("c")).where("metres <= reach").select("level", F.col("dst").alias("node"), "c", "metres", F.lit(True).alias("home"))
    return there.unionByName(home)


def clustered(trips: DataFrame, levels: tuple[Level, ...], engine: str = "auto") -> DataFrame:
    """(level, cluster_id, node_id, metres) of all levels. Where all round trips that they ask for can be on the driver,
    these are taken there once."""
    if engine == "auto":
        found = level_clusters(trips, {v.level: v.radius for v in levels})
        if found is not None:
            return found
    out = None
    for v in levels:
        found = dominating_clusters(dominating_sets(trips, v.radius), engine)
        one = found.select(F.lit(v.level).alias("level"), "cluster_id", "node_id", F.col("metres").cast("long").alias("metres"))
        out = one if out is None else out.unionByName(one)
    return out


def visits_of(points: DataFrame, rule: str) -> DataFrame | None:
    return materialize(points.groupBy("node_id").agg(F.countDistinct("path_id").alias("n")), "visits") if rule == "busiest" else None


def with_sites(index: Index, sites: DataFrame) -> Index:
    """The index with other candidate sites; its representatives are found anew and written."""
    held = materialize(sites.select("site_id").distinct(), "index-sites")
    return replace(index, sites=held, reps=materialize(representatives(index.member, held, index.rule, index.visits), "index-reps"))


def stored(df: DataFrame, name: str) -> DataFrame:
    path = fresh_path(df.sparkSession, name)
    write_partitioned(df, path, "level")
    return df.sparkSession.read.schema(df.schema).parquet(path)


def estimated_detours(index: Index, level: int, existing: tuple[int, ...] = ()) -> DataFrame:
    """(path_id, site_id, metres) to the representatives of a level: path to its own cluster's centre, centre to
    centre, centre to representative; the least over the path's clusters. Never below the true detour. existing: other
    sites to which detours are estimated alike, over the centres of their clusters."""
    at = F.col("level") == level
    own = index.path.where(at).select("cluster_id", "path_id", F.col("metres").alias("to_centre"))
    targets = index.clusters().where(at & F.col("rep").isNotNull()).select(F.col("cluster_id").alias("target"), "rep", "rep_metres")
    if existing:
        open_ = index.member.where(at & F.col("node_id").isin(list(existing))).select(F.col("cluster_id").alias("target"), F.col("node_id").alias("rep"), F.col("metres").alias("rep_metres"))
        targets = targets.unionByName(open_).distinct()
    links = index.link.where(at).select(F.col("cluster_id").alias("from"), F.col("nbr_id").alias("to"), F.col("metres").alias("between"))
    self_links = targets.select(F.col("target").alias("from"), F.col("target").alias("to"), F.lit(0).cast("long").alias("between")).distinct()
    routes = links.unionByName(self_links).join(targets, F.col("to") == F.col("target")).select("from", "rep", (F.col("between") + F.col("rep_metres")).alias("rest"))
    both = own.join(routes, F.col("cluster_id") == F.col("from"))
    return both.groupBy("path_id", F.col("rep").alias("site_id")).agg(F.min(F.col("to_centre") + F.col("rest")).alias("metres"))


def estimated_cover(index: Index, level: int, preference: Preference, existing: tuple[int, ...] = ()) -> DataFrame:
    return times_over(cover(estimated_detours(index, level, existing), preference), index.times)


def index_place(index: Index, spec: PlacementSpec, preference: Preference, n_paths: int, exact_cover: DataFrame | None = None, sketch_copies: int | None = None, site_table: DataFrame | None = None, members: DataFrame | None = None) -> Placement:
    """A query on the index: the greedy with all its constraints over the estimated cover of the level that serves tau,
    with existing sites at their own places. Utilities are estimates, never above the true ones.

    Outside the index's thresholds the greedy runs on exact_cover; only a plain binary query at or above the largest
    one is answered at once: every site serves every path there, so any k do. Sketches are for the plain binary query;
    members(path_id, route): those that the index's paths stand for."""
    spec = replace(spec, mode="auto")
    v = choose_level(index.levels, preference.tau)
    if v is None:
        plain = spec.is_plain() and not spec.existing and preference.name == "binary"
        if exact_cover is None:
            raise ValueError("the threshold is outside the index: give the exact cover")
        if plain and preference.tau >= index.levels[-1].tau_hi:
            return arbitrary_place(index.sites, exact_cover, spec.k, n_paths)
        return greedy_place(exact_cover, spec, n_paths, index.sites if site_table is None else site_table)
    est = materialize(estimated_cover(index, v.level, preference, spec.existing).select("path_id", "site_id", "score"), "estimated-cover")
    try:
        if sketch_copies:
            if not spec.is_plain() or spec.existing or preference.name != "binary":
                raise ValueError("sketches are for the plain binary query")
            return greedy_place_sketch(est, spec.k, n_paths, sketch_copies, members=members)
        reps = index.clusters().where((F.col("level") == v.level) & F.col("rep").isNotNull()).select(F.col("rep").alias("site_id")).distinct()
        return greedy_place(est, spec, n_paths, reps if site_table is None else reps.join(site_table, "site_id"))
    finally:
        discard(est)


def index_stats(index: Index) -> DataFrame:
    """Per level: clusters, mean nodes a cluster, mean paths a cluster, mean neighbours."""
    spark = index.member.sparkSession
    plan = spark.createDataFrame([(v.level, v.radius) for v in index.levels], "level int, radius double")
    m = index.member.groupBy("level").agg(F.countDistinct("cluster_id").alias("n_clusters"), F.count("*").alias("n_nodes"))
    p = index.path.groupBy("level").agg(F.count("*").alias("n_paths"))
    n = index.link.groupBy("level").agg(F.count("*").alias("n_links"))
    joined = plan.join(m, "level").join(p, "level", "left").join(n, "level", "left")
    mean = lambda c: F.round(F.coalesce(c, F.lit(0)) / F.col("n_clusters"), 6)
    return joined.select("level", F.round("radius", 6).alias("radius"), "n_clusters", mean("n_nodes").alias("mean_nodes"), mean("n_paths").alias("mean_paths"), mean("n_links").alias("mean_links"))


# -- updates


def add_sites(index: Index, ids: DataFrame) -> Index:
    """Sites at nodes that the network has: tagged; they lead a cluster that has none, or if they are closer."""
    return with_sites(index, index.sites.unionByName(ids.select("site_id")))


def delete_sites(index: Index, ids: DataFrame) -> Index:
    return with_sites(index, index.sites.join(ids.select("site_id"), "site_id", "left_anti"))


def add_paths(index: Index, points: DataFrame, dist: DataFrame, kernel: bool = True) -> Index:
    """New paths are mapped to the clusters of every level; only their own rows are made. A path that the index has is
    replaced."""
    fresh = materialize(cluster_paths(points, index.member, dist, kernel), "index-fresh")
    kept = index.path.select("level", "cluster_id", "path_id", "metres").join(points.select("path_id").distinct(), "path_id", "left_anti")
    return replace(index, path=materialize(kept.select(*fresh.columns).unionByName(fresh), "index-path"))


def delete_paths(index: Index, ids: DataFrame) -> Index:
    return replace(index, path=materialize(index.path.join(ids.select("path_id"), "path_id", "left_anti").select("level", "cluster_id", "path_id", "metres"), "index-path"))


def add_node_site(index: Index, node_id: int, trips: DataFrame, neighbours: list[int], points: DataFrame | None = None, dist: DataFrame | None = None) -> Index:
    """A site at a new node. trips: round trips that include the new node. Its nearest centre is estimated through its
    network neighbours (round trip to one, and from there to its centre); where that is beyond 2R the node becomes the
    centre of a cluster of its own, with links and paths; the stored round trip is exact."""
    spark = index.member.sparkSession
    legs = trips.where((F.col("a") == node_id) & F.col("b").isin(neighbours)).select(F.col("b").alias("nb"), F.col("metres").alias("leg"))
    guess = index.member.join(legs, F.col("node_id") == F.col("nb")).groupBy("level").agg(F.min(F.struct((F.col("leg") + F.col("metres")).alias("m"), "cluster_id")).alias("g")).select("level", F.col("g.m").alias("m"), F.col("g.cluster_id").alias("centre"))
    plan = spark.createDataFrame([(v.level, v.radius) for v in index.levels], "level int, radius double")
    placed = plan.join(guess, "level", "left").withColumn("joins", F.coalesce(F.col("m") <= 2 * F.col("radius"), F.lit(False)))
    exact = trips.where(F.col("a") == node_id).select(F.col("b").alias("to"), F.col("metres").alias("exact"))
    joined = placed.where("joins").join(exact, F.col("centre") == F.col("to")).select("level", F.col("centre").alias("cluster_id"), F.lit(node_id).cast("long").alias("node_id"), F.col("exact").cast("long").alias("metres"))
    alone = placed.where("not joins").select("level", F.lit(node_id).cast("long").alias("cluster_id"), F.lit(node_id).cast("long").alias("node_id"), F.lit(0).cast("long").alias("metres"))
    fresh = materialize(joined.unionByName(alone), "index-new")
    member = materialize(index.member.select("level", "cluster_id", "node_id", "metres").unionByName(fresh), "index-member")
    out = replace(index, member=member, link=materialize(cluster_links(member, trips, index.levels, index.eps), "index-link"))
    if points is not None:  # paths through the new node pass its cluster; to old centres they pass already
        mine = points.join(points.where(F.col("node_id") == node_id).select("path_id").distinct(), "path_id", "left_semi")
        extra = materialize(cluster_paths(mine, fresh, dist, kernel=False), "index-new-paths")
        kept = index.path.select("level", "cluster_id", "path_id", "metres").join(extra.select("level", "cluster_id", "path_id"), ["level", "cluster_id", "path_id"], "left_anti")
        out = replace(out, path=materialize(kept.select(*extra.columns).unionByName(extra), "index-path"))
    return add_sites(out, spark.createDataFrame([(node_id,)], "site_id long"))


@dataclass(frozen=True)
class UpdateBatch:
    new_sites: DataFrame | None = None
    old_sites: DataFrame | None = None
    new_points: DataFrame | None = None
    old_paths: DataFrame | None = None


def apply_updates(index: Index, batch: UpdateBatch, dist: DataFrame) -> Index:
    """A batch, grouped by kind: deletions first, then additions. The same state as one by one in that order."""
    if batch.old_sites is not None:
        index = delete_sites(index, batch.old_sites)
    if batch.old_paths is not None:
        index = delete_paths(index, batch.old_paths)
    if batch.new_sites is not None:
        index = add_sites(index, batch.new_sites)
    if batch.new_points is not None:
        index = add_paths(index, batch.new_points, dist)
    return index
