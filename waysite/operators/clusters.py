"""Clusters of nodes by round-trip dominance, and the rejected alternative, clusters of sites by similar covers."""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from waysite.operators.sketch import estimates, fm_sketch, hashed
from waysite.sources.tables import materialize

#: Dominance rows that the sequential clustering takes to the driver at most, 20 bytes each: 200 MB; above, peer rounds
#: do the same.
MOST_DRIVER_ROWS = 10_000_000
#: Rows of the cover by which similar covers are still compared.
MOST_COMPARED = 50_000_000
#: Sites whose numbers of common paths a task still adds up as one matrix: 8 bytes a pair, 32 MB, and as much for its sets.
MOST_MATRIX_SITES = 2_000


def dominating_sets(trips: DataFrame, radius: float) -> DataFrame:
    """trips(a, b, metres) round trips -> (node, dominated, metres): all within 2 * radius, the node itself included."""
    return trips.where(F.col("metres") <= 2 * radius).select(F.col("a").alias("node"), F.col("b").alias("dominated"), "metres")


def dominating_clusters(dom: DataFrame, engine: str = "auto", sketch_copies: int | None = None) -> DataFrame:
    """dom(node, dominated, metres) -> (cluster_id, node_id, metres): greedy dominating clusters, named by their centre.

    The centre is each time the free node that dominates most free nodes (ties: smaller id); what it dominates of the
    free nodes is its cluster. engine: driver (compact arrays), peers (rounds over DataFrames, the same result), or
    auto by the number of rows. sketch_copies: counts estimated from sketches instead, on the driver."""
    if engine == "auto":
        engine = "driver" if dom.limit(MOST_DRIVER_ROWS + 1).count() <= MOST_DRIVER_ROWS else "peers"
    if sketch_copies:
        if dom.limit(MOST_DRIVER_ROWS + 1).count() > MOST_DRIVER_ROWS:
            raise ValueError("too many dominance rows for the sketched clustering; use peers")
        return _by_sketch(dom, sketch_copies)
    return _by_driver(dom) if engine == "driver" else _by_peers(dom)


@dataclass(frozen=True)
class _Dominance:
    """Dominance rows of a checked number as arrays: what ids[i] dominates is start[i] to start[i + 1] of near."""

    ids: np.ndarray
    start: np.ndarray
    near: np.ndarray
    metres: np.ndarray

    @staticmethod
    def of(dom: DataFrame) -> _Dominance:
        rows = dom.select(F.col("node").cast("long"), F.col("dominated").cast("long"), F.col("metres").cast("int")).toArrow()
        a, b, m = (rows.column(k).to_numpy() for k in range(3))
        ids, at = np.unique(a, return_inverse=True)
        order = np.lexsort((b, at))
        return _Dominance(ids, np.searchsorted(at[order], np.arange(len(ids) + 1)), np.searchsorted(ids, b[order]).astype(np.int32), m[order])

    def within(self, most: float) -> _Dominance:
        """Only rows of so many metres at most. Every node dominates itself at 0, so none goes."""
        kept = self.metres <= most
        return _Dominance(self.ids, np.r_[0, np.cumsum(kept)][self.start], self.near[kept], self.metres[kept])

    def members(self, i: int, free: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        near, metres = self.near[self.start[i] : self.start[i + 1]], self.metres[self.start[i] : self.start[i + 1]]
        return near[free[near]], metres[free[near]]


def _frame(dom: DataFrame, parts: list[tuple[int, np.ndarray, np.ndarray]]) -> DataFrame:
    """(centre, members, metres) of each cluster -> (cluster_id, node_id, metres)."""
    columns = [np.concatenate([x for x in c] or [np.zeros(0, np.int64)]).astype(np.int64) for c in ([np.full(len(n), c) for c, n, _ in parts], [n for _, n, _ in parts], [m for _, _, m in parts])]
    return dom.sparkSession.createDataFrame(pd.DataFrame(dict(zip(("cluster_id", "node_id", "metres"), columns, strict=True))), "cluster_id long, node_id long, metres long")


def level_clusters(trips: DataFrame, radii: dict[int, float]) -> DataFrame | None:
    """(level, cluster_id, node_id, metres): dominating_clusters of each radius from one reading of the round trips; None:
    there are more rows than the driver takes."""
    dom = dominating_sets(trips, max(radii.values()))
    if dom.limit(MOST_DRIVER_ROWS + 1).count() > MOST_DRIVER_ROWS:
        return None
    held = _Dominance.of(dom)
    parts = [(level, *_clusters(held.within(2 * r))) for level, r in radii.items()]
    columns = [np.concatenate([np.full(len(c), level, np.int32) for level, c, _, _ in parts]), *(np.concatenate([p[k] for p in parts]) for k in (1, 2, 3))]
    return trips.sparkSession.createDataFrame(pa.table(dict(zip(("level", "cluster_id", "node_id", "metres"), columns, strict=True))))


def _clusters(held: _Dominance) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Centre, member and metres of each node's cluster."""
    free, count = np.ones(len(held.ids), bool), np.diff(held.start)
    # A node that dominates itself alone is dominated by no other: a cluster of its own whenever it is picked.
    alone = count == 1
    free[alone] = False
    centres, nodes, metres = [held.ids[alone]], [held.ids[alone]], [held.metres[held.start[:-1][alone]]]
    heap = [(-int(count[v]), v) for v in np.flatnonzero(free).tolist()]
    heapq.heapify(heap)
    while heap:
        c, v = heapq.heappop(heap)
        if not free[v]:
            continue
        if -c != count[v]:
            heapq.heappush(heap, (-int(count[v]), v))
            continue
        members, far = held.members(v, free)
        centres.append(np.full(len(members), held.ids[v]))
        nodes.append(held.ids[members])
        metres.append(far)
        free[members] = False
        for u in members.tolist():  # dominance is symmetric: those that dominate u are those that u dominates
            count[held.near[held.start[u] : held.start[u + 1]]] -= 1
    return tuple(np.concatenate(x).astype(np.int64) for x in (centres, nodes, metres))


def _by_driver(dom: DataFrame) -> DataFrame:
    columns = dict(zip(("cluster_id", "node_id", "metres"), _clusters(_Dominance.of(dom)), strict=True))
    return dom.sparkSession.createDataFrame(pa.table(columns), "cluster_id long, node_id long, metres long")


def _by_peers(dom: DataFrame, most_rounds: int = 100_000) -> DataFrame:
    """A free node that beats every free node within two hops of dominance would be picked before any of them in any
    order, so all such nodes are picked in one round."""
    dom = materialize(dom.select("node", "dominated", "metres"), "dominance")
    free = materialize(dom.select("node").distinct(), "free")
    picked = []
    for _ in range(most_rounds):
        if free.isEmpty():
            break
        f1, f2 = free.select(F.col("node").alias("f1")), free.select(F.col("node").alias("f2"))
        alive = dom.join(f1, F.col("node") == F.col("f1")).join(f2, F.col("dominated") == F.col("f2")).select("node", "dominated", "metres")
        ranks = alive.groupBy("node").agg(F.struct(F.count("*").alias("c"), (-F.col("node")).alias("o")).alias("rank"))
        own = ranks.select(F.col("node").alias("r"), "rank")
        hop1 = alive.join(own, F.col("dominated") == F.col("r")).groupBy("node").agg(F.max("rank").alias("top"))
        top1 = hop1.select(F.col("node").alias("t"), "top")
        hop2 = alive.join(top1, F.col("dominated") == F.col("t")).groupBy("node").agg(F.max("top").alias("top"))
        winners = hop2.join(own, F.col("node") == F.col("r")).where(F.col("top") == F.col("rank")).select(F.col("node").alias("win"))
        taken = materialize(alive.join(winners, F.col("node") == F.col("win")).select(F.col("node").alias("cluster_id"), F.col("dominated").alias("node_id"), "metres"), "clusters")
        picked.append(taken)
        free = materialize(free.join(taken.select("node_id"), F.col("node") == F.col("node_id"), "left_anti"), "free")
    out = picked[0] if picked else _frame(dom, [])
    for p in picked[1:]:
        out = out.unionByName(p)
    return out


def _by_sketch(dom: DataFrame, f: int) -> DataFrame:
    """Counts of free dominated nodes as estimate(union with what is taken) - estimate(what is taken): a sketch can't
    lose members, but it can tell what a union adds."""
    rows = fm_sketch(dom, "node", "dominated", f).toPandas().sort_values(["node", "copy"])
    held = _Dominance.of(dom)
    words = rows["word"].to_numpy(np.int64).reshape(len(held.ids), f)
    free, base, parts = np.ones(len(held.ids), bool), np.zeros(f, np.int64), []
    while free.any():
        live = np.flatnonzero(free)
        gains = estimates(words[live] | base) - (estimates(base[None])[0] if base.any() else 0.0)
        centre = int(live[np.lexsort((live, -gains))[0]])
        members, metres = held.members(centre, free)
        parts.append((int(held.ids[centre]), held.ids[members], metres))
        free[members] = False
        base = base | words[centre]
    return _frame(dom, parts)


def jaccard_pairs(cover: DataFrame, threshold: float) -> DataFrame:
    """(a, b, both, either): pairs of sites whose sets of covered paths are at Jaccard threshold or more.

    Every path pairs all of its sites, which is why the reference rejects it: more than MOST_COMPARED pairs are an error.
    similar_pairs has no such limit."""
    pairs_made = cover.groupBy("path_id").agg(F.count("*").alias("n")).agg(F.coalesce(F.sum(F.col("n") * (F.col("n") - 1) / 2), F.lit(0.0))).first()[0]
    if pairs_made > MOST_COMPARED:
        raise ValueError(f"{pairs_made:.0f} pairs to compare; use similar_pairs, minhash_pairs or the index")
    return _verified(cover, _co_covering(cover), threshold)


def _co_covering(cover: DataFrame) -> DataFrame:
    left = cover.select("path_id", F.col("site_id").alias("a"))
    return left.join(cover.select("path_id", F.col("site_id").alias("b")), "path_id").where("a < b").groupBy("a", "b").agg(F.count("*").alias("both"))


def similar_pairs(cover: DataFrame, threshold: float) -> DataFrame:
    """The same pairs as jaccard_pairs, for covers of any size: paths that the same sites cover are one set with their
    number (a column times of the cover is such a number already), and for up to MOST_MATRIX_SITES sites a task adds up its
    sets as products of matrices instead of rows of pairs."""
    times = F.max("times") if "times" in cover.columns else F.lit(1).cast("long")
    sets = cover.groupBy("path_id").agg(F.sort_array(F.collect_set(F.col("site_id").cast("long"))).alias("sites"), times.alias("times")).groupBy("sites").agg(F.sum("times").alias("times"))
    ids = np.array(sorted(r[0] for r in cover.select("site_id").distinct().limit(MOST_MATRIX_SITES + 1).collect()), np.int64)
    if len(ids) <= MOST_MATRIX_SITES:
        counted = sets.mapInPandas(_common_paths(ids), "a long, b long, both long")
    else:
        firsts = sets.select("times", "sites", F.explode("sites").alias("a"))
        counted = firsts.select("a", F.explode(F.filter("sites", lambda s: s > F.col("a"))).alias("b"), F.col("times").alias("both"))
    return _verified(cover, counted.groupBy("a", "b").agg(F.sum("both").alias("both")), threshold)


def _common_paths(ids: np.ndarray, at_once: int = 2_000):
    """The number of paths that two sites have in common among a task's sets."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total = np.zeros((len(ids), len(ids)))  # whole numbers below 2^53
        for frame in frames:
            for at in range(0, len(frame), at_once):
                part = frame.iloc[at : at + at_once]
                held = np.zeros((len(part), len(ids)))
                lengths = np.fromiter(map(len, part["sites"]), np.int64, len(part))
                held[np.repeat(np.arange(len(part)), lengths), np.searchsorted(ids, np.concatenate(part["sites"].to_list()))] = 1
                total += held.T @ (held * part["times"].to_numpy()[:, None])
        a, b = np.nonzero(np.triu(total, 1))
        yield pd.DataFrame({"a": ids[a], "b": ids[b], "both": total[a, b].astype(np.int64)})

    return run


def _verified(cover: DataFrame, counted: DataFrame, threshold: float) -> DataFrame:
    sizes = cover.groupBy("site_id").agg((F.sum("times") if "times" in cover.columns else F.count("*")).alias("n"))
    sized = counted.join(sizes.select(F.col("site_id").alias("a"), F.col("n").alias("na")), "a").join(sizes.select(F.col("site_id").alias("b"), F.col("n").alias("nb")), "b")
    return sized.select("a", "b", "both", (F.col("na") + F.col("nb") - F.col("both")).alias("either")).where(F.col("both") >= threshold * F.col("either"))


def minhash_pairs(cover: DataFrame, threshold: float, bands: int = 32, rows: int = 2) -> DataFrame:
    """As jaccard_pairs, but only sites that agree on a band of minimum hashes are compared, on their whole sets: a pair
    at similarity s is found with a chance of 1 - (1 - s^rows)^bands."""
    copies = cover.select("site_id", "path_id", F.explode(F.sequence(F.lit(0), F.lit(bands * rows - 1))).alias("copy"))
    least = copies.groupBy("site_id", F.floor(F.col("copy") / rows).alias("band"), (F.col("copy") % rows).alias("row")).agg(F.min(hashed(F.col("path_id"), F.col("copy"), bands * rows)).alias("h"))
    keys = least.groupBy("site_id", "band").agg(F.array_sort(F.collect_list(F.struct("row", "h"))).alias("key"))
    other = keys.select(F.col("site_id").alias("b"), F.col("band").alias("band_b"), F.col("key").alias("key_b"))
    near = keys.join(other, (F.col("band") == F.col("band_b")) & (F.col("key") == F.col("key_b")) & (F.col("site_id") < F.col("b"))).select(F.col("site_id").alias("a"), "b").distinct()
    one = near.join(cover.select(F.col("site_id").alias("a"), "path_id"), "a")
    both = one.join(cover.select(F.col("site_id").alias("b"), F.col("path_id").alias("p")), ["b"]).where("path_id = p").groupBy("a", "b").agg(F.count("*").alias("both"))
    return _verified(cover, both, threshold)


def jaccard_clusters(cover: DataFrame, threshold: float, minhash: bool = False) -> DataFrame:
    """Clusters of sites with similar covers at one fixed threshold of detour, that of the cover given. Leaders: sites by
    weight (ties: smaller id); each joins the first leader similar enough, or leads. One number a site and its similar
    ones are on the driver; their number is checked."""
    weights = [r["site_id"] for r in cover.groupBy("site_id").agg(F.sum("score").alias("w")).orderBy(F.col("w").desc(), "site_id").limit(MOST_DRIVER_ROWS).collect()]
    found = materialize((minhash_pairs if minhash else similar_pairs)(cover, threshold), "similar")
    if found.count() > MOST_DRIVER_ROWS:
        raise ValueError("too many similar sites to lead one after the other")
    near: dict[int, set[int]] = {}
    for r in found.toLocalIterator():
        near.setdefault(r["a"], set()).add(r["b"])
        near.setdefault(r["b"], set()).add(r["a"])
    leader: dict[int, int] = {}
    place: dict[int, int] = {}
    for s in weights:
        leads = [m for m in near.get(s, ()) if m in place]
        leader[s] = min(leads, key=place.__getitem__) if leads else s
        if not leads:
            place[s] = len(place)
    return cover.sparkSession.createDataFrame([(m, s) for s, m in leader.items()], "cluster_id long, site_id long")
