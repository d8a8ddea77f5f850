"""Detours of paths to sites, and the covering relation made from them."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from waysite.functions.preference import Preference
from waysite.operators.distance import network_distances
from waysite.sources.tables import materialize

PAIRS = ("any", "same", "forward", "forward_along")
#: Nodes of a network whose full distance matrix (4 bytes a pair) is still broadcast to the kernel: 64 MB.
MOST_KERNEL_NODES = 4_000
#: Longer than any way, and small enough to be added three times in 32 bits.
FAR = 1 << 29


def detours(points: DataFrame, sites: DataFrame, dist: DataFrame, pair: str = "any") -> DataFrame:
    """points(path_id, seq, node_id), sites(site_id), dist(src, dst, metres) -> (path_id, site_id, metres).

    The least extra length of leaving the path at one of its nodes for the site and rejoining it at another, by joins.
    pair: any (two nodes in any order), same (rejoin where it left), forward (rejoin not before), forward_along (as
    forward, with the gap measured along the path). A site that a path cannot reach has no row."""
    out = dist.select(F.col("src").alias("v"), F.col("dst").alias("s"), F.col("metres").alias("there"))
    back = dist.select(F.col("src").alias("s2"), F.col("dst").alias("w"), F.col("metres").alias("return"))
    held = sites.select(F.col("site_id").alias("s"))
    if pair == "same":
        nodes = points.select("path_id", "node_id").distinct()
        both = nodes.join(out, F.col("node_id") == F.col("v")).join(held, "s", "left_semi").join(back, (F.col("s") == F.col("s2")) & (F.col("node_id") == F.col("w")))
        return both.groupBy("path_id", F.col("s").alias("site_id")).agg(F.min(F.col("there") + F.col("return")).alias("metres"))
    if pair == "forward_along":
        return along_detours(points, held, out, back, dist)
    ordered = pair == "forward"
    keys = ["path_id", "seq", "node_id"] if ordered else ["path_id", "node_id"]
    nodes = points.select(*keys) if ordered else points.select(*keys).distinct()
    leave = nodes.select("path_id", *([F.col("seq").alias("seq_v")] if ordered else []), F.col("node_id").alias("leave"))
    rejoin = nodes.select(F.col("path_id").alias("p2"), *([F.col("seq").alias("seq_w")] if ordered else []), F.col("node_id").alias("rejoin"))
    order = (F.col("path_id") == F.col("p2")) & (F.col("seq_w") >= F.col("seq_v")) if ordered else F.col("path_id") == F.col("p2")
    # Pairs of nodes repeat over paths: each pair's saving and each site's way round it are joined once a distinct pair.
    pairs = leave.join(rejoin, order).select("path_id", "leave", "rejoin").distinct()
    gaps = dist.select(F.col("src").alias("g_v"), F.col("dst").alias("g_w"), F.col("metres").alias("gap"))
    distinct = pairs.select("leave", "rejoin").distinct().join(gaps, (F.col("leave") == F.col("g_v")) & (F.col("rejoin") == F.col("g_w")))
    round_way = distinct.join(out.join(held, "s", "left_semi"), F.col("leave") == F.col("v")).join(back, (F.col("s") == F.col("s2")) & (F.col("rejoin") == F.col("w")))
    extra = round_way.select(F.col("leave").alias("l"), F.col("rejoin").alias("r"), "s", (F.col("there") + F.col("return") - F.col("gap")).alias("metres"))
    met = pairs.join(extra, (F.col("leave") == F.col("l")) & (F.col("rejoin") == F.col("r")))
    return met.groupBy("path_id", F.col("s").alias("site_id")).agg(F.min("metres").alias("metres"))


def along_detours(points: DataFrame, held: DataFrame, out: DataFrame, back: DataFrame, dist: DataFrame) -> DataFrame:
    """Linear in the path: with P the length along the path so far, the best leave up to a rejoin is a running minimum
    of way there + P, and the detour the least of way back - P plus it, never below 0."""
    w = Window.partitionBy("path_id").orderBy("seq")
    steps = dist.select(F.col("src").alias("g_v"), F.col("dst").alias("g_w"), F.col("metres").alias("gap"))
    linked = points.select("path_id", "seq", "node_id", F.lag("node_id").over(w).alias("last")).join(steps, (F.col("last") == F.col("g_v")) & (F.col("node_id") == F.col("g_w")), "left")
    placed = linked.select("path_id", "seq", "node_id", F.sum(F.coalesce("gap", F.lit(0))).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("along"))
    ways = placed.join(out.join(held, "s", "left_semi"), F.col("node_id") == F.col("v")).join(back, (F.col("s") == F.col("s2")) & (F.col("node_id") == F.col("w")))
    run = Window.partitionBy("path_id", "s").orderBy("seq").rowsBetween(Window.unboundedPreceding, 0)
    best = ways.select("path_id", "s", (F.col("return") - F.col("along") + F.min(F.col("there") + F.col("along")).over(run)).alias("extra"))
    return best.groupBy("path_id", F.col("s").alias("site_id")).agg(F.greatest(F.min("extra"), F.lit(0)).cast("long").alias("metres"))


@dataclass(frozen=True)
class Matrix:
    """All distances of a network of up to MOST_KERNEL_NODES nodes; FAR where there is no way."""

    ids: np.ndarray
    metres: np.ndarray

    @staticmethod
    def of(dist: DataFrame) -> Matrix:
        if dist.select("src").distinct().limit(MOST_KERNEL_NODES + 1).count() > MOST_KERNEL_NODES:
            raise ValueError("network too large for the matrix kernel; use detours()")
        rows = dist.select(*(F.col(c).cast(k) for c, k in (("src", "long"), ("dst", "long"), ("metres", "int")))).toArrow()
        src, dst, metres = (rows.column(k).to_numpy() for k in range(3))
        ids = np.unique(np.concatenate([src, dst]))
        out = np.full((len(ids), len(ids)), FAR, np.int32)
        out[np.searchsorted(ids, src), np.searchsorted(ids, dst)] = metres
        return Matrix(ids, out)

    def detours(self, nodes: np.ndarray, sites: np.ndarray) -> np.ndarray:
        """The least detour from the nodes of a path to each site: a minimum over all pairs of nodes, one leave at a time.
        Nodes that the network doesn't have lead nowhere."""
        nodes = nodes[np.isin(nodes, self.ids)]
        at, columns = np.searchsorted(self.ids, nodes), np.searchsorted(self.ids, sites)
        inner = self.metres[np.ix_(at, at)]
        inner = np.where(inner < FAR, inner, -FAR)
        there, home = self.metres[np.ix_(at, columns)], np.ascontiguousarray(self.metres[np.ix_(columns, at)].T)
        best = np.full(len(columns), FAR, np.int32)
        for i in range(len(at)):
            np.minimum(best, there[i] + (home - inner[i][:, None]).min(0), out=best)
        return best


def kernel_detours(points: DataFrame, sites: DataFrame, dist: DataFrame, tau: int | None = None) -> DataFrame:
    """The same as detours(pair="any") on networks of up to MOST_KERNEL_NODES nodes: the distance matrix is broadcast
    and each distinct set of path nodes is one numpy step, shared by all paths that have it."""
    matrix = Matrix.of(dist)
    chosen = np.sort(sites.select("site_id").toPandas()["site_id"].to_numpy())  # a site is a node of the network
    chosen = chosen[np.isin(chosen, matrix.ids)]
    routes = route_arrays(points)
    once = numbered_routes(routes.select("nodes").distinct().withColumn("goals", F.lit(None).cast("array<long>")))
    found = run_kernel(once, matrix, FAR // 2 if tau is None else int(tau), chosen)
    # Up to one row a route and site, many times the estimate made from the routes: never to be broadcast.
    return routes.join(once.select("nodes", "route"), "nodes").join(found.hint("merge"), "route").select("path_id", "site_id", "metres")


def own_detours(through: DataFrame, points: DataFrame, dist: DataFrame, kernel: bool = True) -> DataFrame:
    """through(path_id, site_id) -> (path_id, site_id, metres): the detours of these pairs only. Sites on a path cost
    nothing and need no distance."""
    routes = route_arrays(points)
    placed = through.select("path_id", "site_id").distinct().join(routes, "path_id")
    here = placed.where(F.array_contains("nodes", F.col("site_id"))).select("path_id", "site_id", F.lit(0).cast("long").alias("metres"))
    off = placed.where(~F.array_contains("nodes", F.col("site_id")))
    if not kernel:
        ids = off.select("path_id", "site_id")
        met = points.select("path_id", "node_id").distinct().join(ids, "path_id")
        there = dist.select(F.col("src").alias("v"), F.col("dst").alias("s"), F.col("metres").alias("out"))
        back = dist.select(F.col("src").alias("s2"), F.col("dst").alias("w"), F.col("metres").alias("home"))
        gap = dist.select(F.col("src").alias("g1"), F.col("dst").alias("g2"), F.col("metres").alias("gap"))
        leave = met.join(there, (F.col("node_id") == F.col("v")) & (F.col("site_id") == F.col("s"))).select("path_id", "site_id", "v", "out")
        rejoin = met.join(back, (F.col("site_id") == F.col("s2")) & (F.col("node_id") == F.col("w"))).select("path_id", "site_id", "w", "home")
        both = leave.join(rejoin, ["path_id", "site_id"]).join(gap, (F.col("v") == F.col("g1")) & (F.col("w") == F.col("g2")))
        return here.unionByName(both.groupBy("path_id", "site_id").agg(F.min(F.col("out") + F.col("home") - F.col("gap")).cast("long").alias("metres")))
    # What a path's clusters are follows from its nodes, so equal routes have equal goals: at most the network's nodes.
    grouped = numbered_routes(off.groupBy("nodes").agg(F.collect_set("site_id").alias("goals")))
    found = run_kernel(grouped, Matrix.of(dist), FAR // 2, None)
    away = off.join(grouped.select("nodes", "route"), "nodes").select("path_id", F.col("site_id").alias("s"), F.col("route").alias("r"))
    met = away.join(found.hint("merge"), (F.col("r") == F.col("route")) & (F.col("s") == F.col("site_id")))
    return here.unionByName(met.select("path_id", "site_id", "metres"))


def route_arrays(points: DataFrame) -> DataFrame:
    """(path_id, nodes): the set of a path's nodes in ascending order."""
    return points.groupBy("path_id").agg(F.sort_array(F.collect_set("node_id")).alias("nodes"))


def counted_routes(points: DataFrame) -> DataFrame:
    """(route, nodes, times): paths of equal sets of nodes as one, with the least path_id for its number."""
    return route_arrays(points).groupBy("nodes").agg(F.min("path_id").alias("route"), F.count("*").alias("times"))


def route_points(routes: DataFrame) -> DataFrame:
    """Routes as paths; the order of a route's nodes is that of their ids."""
    return routes.select(F.col("route").alias("path_id"), F.posexplode("nodes").alias("seq", "node_id"), F.lit(None).cast("timestamp").alias("ts"))


def times_over(covering: DataFrame, times: DataFrame | None) -> DataFrame:
    """A cover of paths that stand for several: scores times their number, which stays as a column."""
    if times is None:
        return covering
    number = times.select(F.col("path_id").alias("stands"), "times")
    return covering.join(number, F.col("path_id") == F.col("stands")).drop("stands").withColumn("score", F.col("score") * F.col("times"))


def numbered_routes(routes: DataFrame) -> DataFrame:
    """routes(nodes, goals) with a number for each: written, so that the numbers stay."""
    return materialize(routes.withColumn("route", F.monotonically_increasing_id()), "routes")


def run_kernel(routes: DataFrame, matrix: Matrix, most: int, chosen: np.ndarray | None) -> DataFrame:
    """routes(route, nodes, goals) -> (route, site_id, metres): detours up to `most` to the chosen sites, or to each
    route's goals."""
    shared = routes.sparkSession.sparkContext.broadcast((matrix, chosen))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        matrix, chosen = shared.value
        for frame in frames:
            keys, sites_of, metres = [], [], []
            for route, nodes, goals in zip(frame["route"], frame["nodes"], frame["goals"], strict=True):
                sites = np.asarray(goals, np.int64) if chosen is None else chosen
                best = matrix.detours(np.asarray(nodes), sites)
                ok = best <= most
                keys.append(np.full(int(ok.sum()), route))
                sites_of.append(sites[ok])
                metres.append(best[ok].astype(np.int64))
            if keys:
                yield pd.DataFrame({"route": np.concatenate(keys), "site_id": np.concatenate(sites_of), "metres": np.concatenate(metres)})

    return routes.select("route", "nodes", "goals").mapInPandas(run, "route long, site_id long, metres long")


def ranked_detours(detour: DataFrame) -> DataFrame:
    """Each detour's rank among those of its site and of its path, nearest first (ties by id)."""
    by_site = Window.partitionBy("site_id").orderBy("metres", "path_id")
    by_path = Window.partitionBy("path_id").orderBy("metres", "site_id")
    return detour.select("path_id", "site_id", "metres", F.row_number().over(by_site).alias("site_rank"), F.row_number().over(by_path).alias("path_rank"))


def cover(detour: DataFrame, preference: Preference) -> DataFrame:
    """(path_id, site_id, metres, score): the pairs within tau, scored. Pairs that score nothing don't cover."""
    kept = detour if preference.tau is None else detour.where(F.col("metres") <= preference.tau)
    scored = kept.select("path_id", "site_id", "metres", preference.score(F.col("metres")).alias("score"))
    return scored if preference.tau is None else scored.where("score > 0")


def cover_at_query(edges: DataFrame, points: DataFrame, sites: DataFrame, tau: int, preference: Preference) -> DataFrame:
    """The cover without anything stored: all searches are made when the query comes. First the distances between the
    nodes of each path, which tell how far the others have to go."""
    nodes = points.select("path_id", "node_id").distinct()
    pairs = nodes.join(nodes.select("path_id", F.col("node_id").alias("to")), "path_id").select(F.col("node_id").alias("src"), F.col("to").alias("dst")).distinct()
    within = materialize(network_distances(edges, nodes, wanted=pairs), "within-paths")
    horizon = tau + int(within.agg(F.max("metres")).first()[0] or 0)
    starts = points.select("node_id").unionByName(sites.select(F.col("site_id").alias("node_id"))).distinct()
    return cover(detours(points, sites, network_distances(edges, starts, horizon)), preference)


def site_weights(covering: DataFrame) -> DataFrame:
    return covering.groupBy("site_id").agg(F.sum("score").alias("weight"), F.count("*").alias("n_paths"))


def covering_sets(covering: DataFrame, by: str = "site_id") -> DataFrame:
    """The members of each site's (or path's) set, nearest first: for small relations, as a set is one value."""
    other = "path_id" if by == "site_id" else "site_id"
    return covering.groupBy(by).agg(F.array_sort(F.collect_list(F.struct("metres", other))).alias("m")).select(by, F.transform("m", lambda r: r[other]).alias("members"))
