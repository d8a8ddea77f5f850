"""Greedy placement over a covering relation: the plain query and its extensions in one loop.

The driver keeps the chosen sites (at most k) and, in delta mode, one number a site; the covering relation stays
distributed, once by path and once by site. A cover of a checked small size, as an index level has it, is placed on by
one process instead, with the same answers."""

from __future__ import annotations

import heapq
from dataclasses import dataclass, field, replace

import numpy as np
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from waysite.functions.preference import MICRO
from waysite.operators.bits import SiteBits, bit_sums, has_bit, site_bits
from waysite.sources.tables import discard, materialize

#: Rows of a cover that one process takes at most: 24 bytes each, 72 MB.
MOST_ARRAY_ROWS = 3_000_000
#: Rows of a cover from which on it is taken as bits, if it is one of few sites with one score a path.
BIT_ROWS = 300_000
PLACEMENT = "step int, site_id long, gain long, utility long, utility_pct double"


@dataclass(frozen=True)
class PlacementSpec:
    """What is asked for. k sites, or a budget over costs, or a quota (share of paths to serve); capacities limit the
    paths a site serves; existing sites serve already. mode: recompute, delta or lazy (the last two: plain queries), arrays
    (one process), or auto (bits for large covers that can be, else arrays up to MOST_ARRAY_ROWS rows of the cover, checked)."""

    k: int | None = 5
    budget: float | None = None
    quota: float | None = None
    capacity: bool = False
    existing: tuple[int, ...] = ()
    mode: str = "recompute"
    safeguard: bool = True

    def __post_init__(self):
        if self.mode not in ("recompute", "delta", "lazy", "arrays", "auto"):
            raise ValueError(f"unknown mode {self.mode}")
        if self.k is None and self.budget is None and self.quota is None:
            raise ValueError("give k, a budget or a quota")
        if self.mode in ("delta", "lazy") and not self.is_plain():
            raise ValueError("delta and lazy modes are for plain queries")

    def is_plain(self) -> bool:
        """k sites, though some may be open before."""
        return self.budget is None and self.quota is None and not self.capacity


@dataclass
class Placement:
    steps: list[tuple[int, int, int, int]] = field(default_factory=list)  # step, site_id, gain, utility
    n_paths: int = 0
    base: int = 0  # utility of the existing sites
    reached: bool = True  # a quota that cannot be reached: False
    evaluations: int = 0
    seconds: list[float] = field(default_factory=list, compare=False)  # when each step was taken, where that is noted

    @property
    def sites(self) -> list[int]:
        return [s[1] for s in self.steps]

    @property
    def utility(self) -> int:
        return self.steps[-1][3] if self.steps else self.base

    def frame(self, spark) -> DataFrame:
        pct = lambda u: round(u / MICRO / self.n_paths * 100, 6) if self.n_paths else 0.0
        return spark.createDataFrame([(*s, pct(s[3])) for s in self.steps], PLACEMENT)


def greedy_place(cover: DataFrame, spec: PlacementSpec, n_paths: int, sites: DataFrame | None = None) -> Placement:
    """cover(path_id, site_id, score) -> the sites picked by marginal gain.

    Ties: larger gain, then larger weight, then larger site id. A chosen site is never picked again; sites without any
    gain still fill k. sites(site_id[, cost, capacity]) adds candidates that cover nothing, and carries costs and
    capacities; without it the candidates are the sites of the cover."""
    mode = spec.mode
    if mode == "auto":
        number = cover.limit(MOST_ARRAY_ROWS + 1).count()
        if number > BIT_ROWS and not spec.capacity:
            loop = _BitLoop.of(cover, spec, n_paths, sites)
            if loop is not None:
                return loop.plain() if spec.budget is None else loop.budgeted()
        mode = "arrays" if number <= MOST_ARRAY_ROWS else "delta" if spec.is_plain() else "recompute"
    loop = (_ArrayLoop if mode == "arrays" else _FrameLoop)(cover, spec, n_paths, sites)
    try:
        if spec.budget is not None:
            return loop.budgeted()
        return {"delta": loop.delta, "lazy": loop.lazy}[mode]() if mode in ("delta", "lazy") else loop.plain()
    finally:
        loop.close()


class _Loop:
    """The two ways of going on, over a leader that the engines find each in its own way."""

    def __init__(self, spec: PlacementSpec, n_paths: int):
        self.spec, self.n_paths = spec, n_paths
        self.chosen: list[int] = []
        self.out = Placement(n_paths=n_paths)

    def start(self) -> None:
        raise NotImplementedError

    def lead(self, most_cost: float | None = None, per_cost: bool = False) -> tuple[int, int, float] | None:
        """(site, gain, cost) of the best site that is not open and costs most_cost at most."""
        raise NotImplementedError

    def serve(self, site: int) -> None:
        raise NotImplementedError

    def close(self) -> None:
        pass

    def open_ids(self) -> list[int]:
        return [*self.spec.existing, *self.chosen]

    def take(self, site: int, gain: int) -> None:
        self.serve(site)
        self.chosen.append(site)
        self.out.steps.append((len(self.chosen), site, gain, self.out.utility + gain))

    def plain(self) -> Placement:
        self.start()
        want = None if self.spec.quota is None else -(-int(round(self.spec.quota * self.n_paths * MICRO)) // MICRO) * MICRO
        while self.spec.k is None or len(self.chosen) < self.spec.k:
            if want is not None and self.out.utility >= want:
                break
            top = self.lead()
            self.out.evaluations += 1
            if top is None or (want is not None and top[1] == 0):
                self.out.reached = want is None or self.out.utility >= want
                break
            self.take(top[0], top[1])
        return self.out

    def budgeted(self) -> Placement:
        """Largest gain for its cost; a site above what is left is out for good, as less is left later; at the end the best
        affordable single site is taken instead if it alone is better."""
        self.start()
        left = float(self.spec.budget)
        single = self.lead(left)
        while self.spec.k is None or len(self.chosen) < self.spec.k:
            top = self.lead(left, per_cost=True)
            if top is None:
                break
            self.take(top[0], top[1])
            left = round(left - top[2], 9)
        if self.spec.safeguard and single is not None and self.out.base + single[1] > self.out.utility:
            self.out.steps = [(1, single[0], single[1], self.out.base + single[1])]
        return self.out


class _ArrayLoop(_Loop):
    """Covers of a checked size, as numpy arrays of one process."""

    def __init__(self, cover: DataFrame, spec: PlacementSpec, n_paths: int, sites: DataFrame | None):
        super().__init__(spec, n_paths)
        rows = cover.select(*(F.col(c).cast("long") for c in ("path_id", "site_id", "score"))).toArrow()
        path, site, self.score = (rows.column(k).to_numpy() for k in range(3))
        known = attributes(sites if sites is not None else cover.select("site_id").distinct()).toArrow()
        ids = known.column(0).to_numpy()
        order = np.argsort(ids)
        self.ids = ids[order]
        self.cost = known.column(1).to_numpy()[order]
        room = known.column(2).to_numpy(zero_copy_only=False).astype(float)[order]
        self.room = np.where(np.isnan(room), np.inf, room)
        self.paths, self.path = np.unique(path, return_inverse=True)
        # Open sites need not be candidates; their rows are kept under a number of their own.
        self.all, self.site = np.unique(np.concatenate([site, self.ids, np.array(spec.existing, np.int64)]), return_inverse=True)
        self.site = self.site[: len(site)]
        self.of = np.searchsorted(self.all, self.ids)
        self.u = np.zeros(len(self.paths), np.int64)
        self.weight = self.summed(self.score)

    def summed(self, values: np.ndarray) -> np.ndarray:
        return np.bincount(self.site, weights=values, minlength=len(self.all)).astype(np.int64)

    def start(self) -> None:
        held = np.isin(self.all[self.site], self.spec.existing)
        np.maximum.at(self.u, self.path[held], self.score[held])
        self.out.base = int(self.u.sum())

    def first_by_gain(self, gain: np.ndarray) -> np.ndarray:
        """Each row's place among its site's rows, largest gain first, ties by path."""
        order = np.lexsort((self.path, -gain, self.site))
        starts = np.searchsorted(self.site[order], np.arange(len(self.all)))
        place = np.empty(len(order), np.int64)
        place[order] = np.arange(len(order)) - starts[self.site[order]]
        return place

    def lead(self, most_cost=None, per_cost=False):
        gain = np.maximum(self.score - self.u[self.path], 0)
        if self.spec.capacity:
            room = np.full(len(self.all), np.inf)
            room[self.of] = self.room
            gain = np.where(self.first_by_gain(gain) < room[self.site], gain, 0)
        total, weight = self.summed(gain)[self.of], self.weight[self.of]
        free = ~np.isin(self.ids, self.open_ids()) & (True if most_cost is None else self.cost <= most_cost)
        if not free.any():
            return None
        keys = (self.ids, weight, total, total / self.cost) if per_cost else (self.ids, weight, total)
        best = np.lexsort(tuple(k[free] for k in keys))[-1]
        at = np.flatnonzero(free)[best]
        return int(self.ids[at]), int(total[at]), float(self.cost[at])

    def serve(self, site: int) -> None:
        rows = np.flatnonzero(self.all[self.site] == site)
        if self.spec.capacity:
            gain = self.score[rows] - self.u[self.path[rows]]
            rows = rows[gain > 0][np.lexsort((self.path[rows][gain > 0], -gain[gain > 0]))]
            room = self.room[np.searchsorted(self.ids, site)]
            rows = rows if np.isinf(room) else rows[: int(room)]
        self.u[self.path[rows]] = np.maximum(self.u[self.path[rows]], self.score[rows])


class _BitLoop(_Loop):
    """Covers of few sites with one score a path: the different rows of bits and their scores, less those served already."""

    def __init__(self, bits: SiteBits, held: tuple[np.ndarray, np.ndarray], spec: PlacementSpec, n_paths: int, sites: DataFrame | None):
        super().__init__(spec, n_paths)
        self.words, self.score = held
        self.at = {int(s): i for i, s in enumerate(bits.ids)}
        if sites is None:
            self.ids, self.cost = bits.ids, np.ones(len(bits.ids))
        else:
            known = attributes(sites).toArrow()
            order = np.argsort(known.column(0).to_numpy())
            self.ids, self.cost = (known.column(k).to_numpy()[order] for k in range(2))
        self.weight = self.gains()

    @staticmethod
    def of(cover: DataFrame, spec: PlacementSpec, n_paths: int, sites: DataFrame | None) -> _BitLoop | None:
        bits = site_bits(cover)
        if bits is None:
            return None
        held = bits.merged()
        bits.discard()
        return None if held is None else _BitLoop(bits, held, spec, n_paths, sites)

    def gains(self) -> np.ndarray:
        summed = bit_sums(self.words, self.score, len(self.at))
        return np.array([summed[self.at[s]] if s in self.at else 0 for s in self.ids.tolist()], np.int64)

    def start(self) -> None:
        before = int(self.score.sum())
        for site in self.spec.existing:
            self.serve(site)
        self.out.base = before - int(self.score.sum())

    def lead(self, most_cost=None, per_cost=False):
        free = ~np.isin(self.ids, self.open_ids()) & (True if most_cost is None else self.cost <= most_cost)
        if not free.any():
            return None
        total = self.gains()
        keys = (self.ids, self.weight, total, total / self.cost) if per_cost else (self.ids, self.weight, total)
        at = np.flatnonzero(free)[np.lexsort(tuple(k[free] for k in keys))[-1]]
        return int(self.ids[at]), int(total[at]), float(self.cost[at])

    def serve(self, site: int) -> None:
        if site in self.at:
            left = ~has_bit(self.words, self.at[site])
            self.words, self.score = self.words[left], self.score[left]


class _RouteLoop(_Loop):
    """Capacities over routes: the scores of routes as a table of one process (of a large cover as bits), and each path's route and best score so far in
    order of path_id, 8 bytes a path. Gains of a site never grow, so old ones bound new ones and only leaders are valued."""

    def __init__(self, cover: DataFrame, members: DataFrame, spec: PlacementSpec, n_paths: int, sites: DataFrame, bits: tuple[np.ndarray, tuple] | None = None):
        super().__init__(spec, n_paths)
        known = attributes(sites).toArrow()
        room = known.column(2).to_numpy(zero_copy_only=False).astype(float)
        self.room = {int(i): None if np.isnan(x) else int(x) for i, x in zip(known.column(0).to_numpy(), room, strict=True)}
        self.of, self.bits = {}, None
        if bits is None:
            rows = cover.select(*(F.col(c).cast("long") for c in ("path_id", "site_id", "score"))).toArrow()
            route, site, score = (rows.column(k).to_numpy() for k in range(3))
            routes, at = np.unique(route, return_inverse=True)
            order = np.argsort(site, kind="stable")
            starts = np.flatnonzero(np.r_[True, np.diff(site[order]) > 0]) if len(order) else []
            self.of = {int(site[o[0]]): (at[o], score[o].astype(np.int32)) for o in np.split(order, starts)[1:]} if len(order) else {}
        else:
            ids, (route, words, score) = bits
            order = np.argsort(route)
            routes, self.bits = route[order], ({int(s): i for i, s in enumerate(ids)}, words[order], score[order].astype(np.int32))
        held = members.select(F.col("path_id").cast("long"), F.col("route").cast("long")).toArrow()
        path, named = held.column(0).to_numpy(), held.column(1).to_numpy()
        covered = np.isin(named, routes)
        self.route = np.searchsorted(routes, named[covered][np.argsort(path[covered])]).astype(np.int32)
        self.u, self.n_routes, self.heap = np.zeros(len(self.route), np.int32), len(routes), None
        number = np.bincount(self.route, minlength=len(routes))
        self.weight = {s: int(self.scores(s).astype(np.int64) @ number) for s in (self.of if self.bits is None else self.bits[0])}

    def scores(self, site: int) -> np.ndarray:
        """What the site scores on each route."""
        if self.bits is not None:
            place, words, score = self.bits
            return np.where(has_bit(words, place[site]), score, 0) if site in place else np.zeros(self.n_routes, np.int32)
        score = np.zeros(self.n_routes, np.int32)
        if site in self.of:
            score[self.of[site][0]] = self.of[site][1]
        return score

    def served(self, site: int) -> tuple[np.ndarray, np.ndarray]:
        """Paths that the site would serve and what each gains: the largest first, ties by the lowest path."""
        gain = self.scores(site)[self.route] - self.u
        at, room = np.flatnonzero(gain > 0), self.room[site]
        if room is not None and len(at) > room:
            at = at[np.argsort(-gain[at], kind="stable")[:room]]
        return at, gain[at]

    def start(self) -> None:
        self.heap = [(-w, -w, -s, 0) for s in self.room for w in [self.weight.get(s, 0)]]
        heapq.heapify(self.heap)

    def lead(self, most_cost=None, per_cost=False):
        now = len(self.chosen) + 1
        while self.heap and self.heap[0][3] != now:
            _, w, s, _ = heapq.heappop(self.heap)
            heapq.heappush(self.heap, (-int(self.served(-s)[1].sum(dtype=np.int64)), w, s, now))
        if not self.heap:
            return None
        gain, _, s, _ = heapq.heappop(self.heap)
        return -s, -gain, 1.0

    def serve(self, site: int) -> None:
        at, gain = self.served(site)
        self.u[at] += gain


#: Paths, and rows of the routes' cover, that one process takes: 8 bytes a path and 24 a row.
MOST_MEMBERS = 20_000_000


def capacity_place(cover: DataFrame, members: DataFrame, k: int, n_paths: int, sites: DataFrame, chosen: list[int] | None = None) -> Placement:
    """k sites with capacities over a cover of routes, path_id being the route and score that of one path; members(path_id,
    route) are the paths. The same answer as greedy_place on the cover of the paths, which larger inputs are still given to.
    chosen: these sites open one after the other instead."""
    held, large = None, cover.limit(MOST_ARRAY_ROWS + 1).count() > BIT_ROWS
    few = members.limit(MOST_MEMBERS + 1).count() <= MOST_MEMBERS
    if few and large:
        bits = site_bits(cover)
        if bits is not None:
            found = bits.by_path()
            bits.discard()
            held = None if found is None else (bits.ids, found)
        large = held is None and cover.limit(MOST_ARRAY_ROWS + 1).count() > MOST_ARRAY_ROWS
    if large or not few:
        whole = cover.select(F.col("path_id").alias("r"), "site_id", "score").join(members, F.col("r") == F.col("route")).select("path_id", "site_id", "score")
        if chosen is not None:
            return Placement([(len(chosen), chosen[-1], 0, served_by(whole, chosen, sites))] if chosen else [], n_paths)
        return greedy_place(whole, PlacementSpec(k=k, capacity=True), n_paths, sites)
    loop = _RouteLoop(cover, members, PlacementSpec(k=k, capacity=True), n_paths, sites, held)
    if chosen is None:
        return loop.plain()
    for site in chosen:
        loop.take(site, int(loop.served(site)[1].sum(dtype=np.int64)))
    return loop.out


class _FrameLoop(_Loop):
    """Covers of any size, kept twice: by path, so that corrections meet the cover without shuffling it, and written in
    order of sites, so that the rows of a few sites are read and nothing else."""

    def __init__(self, cover: DataFrame, spec: PlacementSpec, n_paths: int, sites: DataFrame | None):
        super().__init__(spec, n_paths)
        held = cover.select("path_id", "site_id", "score")
        self.by_path = held.repartition("path_id").persist(StorageLevel.DISK_ONLY)
        self.by_site = materialize(self.by_path.repartitionByRange("site_id", "path_id").sortWithinPartitions("site_id", "path_id"), "cover-by-site")
        known = sites if sites is not None else self.by_site.select("site_id").distinct()
        weights = self.by_site.groupBy("site_id").agg(F.sum("score").alias("weight"))
        self.sites = materialize(attributes(known).join(weights, "site_id", "left").withColumn("weight", F.coalesce("weight", F.lit(0).cast("long"))), "cover-sites")
        self.served: DataFrame | None = None  # capacity only: (path_id, u) as served so far

    def close(self) -> None:
        self.by_path.unpersist()
        discard(self.by_site, self.sites)

    def rows_of(self, ids: list[int]) -> DataFrame:
        return self.by_site.where(F.col("site_id").isin(ids) if ids else F.lit(False))

    def best_so_far(self) -> DataFrame:
        """(path_id, u): the best score of each path over the open sites, from the rows of those sites."""
        if self.served is not None:
            return self.served
        return self.rows_of(self.open_ids()).groupBy("path_id").agg(F.max("score").alias("u"))

    def over_best(self, rows: DataFrame) -> DataFrame:
        gain = F.greatest(F.col("score") - F.coalesce(F.col("u"), F.lit(0)), F.lit(0))
        return rows.join(self.best_so_far(), "path_id", "left").select("path_id", "site_id", "score", gain.alias("gain"))

    def gains(self) -> DataFrame:
        """(site_id, gain, weight, cost) of all candidates; while nothing is open the gains are the weights."""
        ids = self.open_ids()
        if not ids and not self.spec.capacity:
            return self.sites.select("site_id", F.col("weight").alias("gain"), "weight", "cost")
        each = self.over_best(self.by_path)
        if self.spec.capacity:
            rank = F.row_number().over(Window.partitionBy("site_id").orderBy(F.col("gain").desc(), "path_id"))
            limited = each.where("gain > 0").join(self.sites.select("site_id", "room"), "site_id")
            each = limited.withColumn("rank", rank).where(F.col("room").isNull() | (F.col("rank") <= F.col("room")))
        summed = each.groupBy("site_id").agg(F.sum("gain").alias("gain"))
        free = self.sites.where(~F.col("site_id").isin(ids)) if ids else self.sites
        return free.join(summed, "site_id", "left").select("site_id", F.coalesce("gain", F.lit(0).cast("long")).alias("gain"), "weight", "cost")

    def start(self) -> None:
        if self.spec.existing:
            if self.spec.capacity:
                self.served = materialize(self.rows_of(list(self.spec.existing)).groupBy("path_id").agg(F.max("score").alias("u")), "served")
            self.out.base = int(self.best_so_far().agg(F.coalesce(F.sum("u"), F.lit(0))).first()[0])

    def lead(self, most_cost=None, per_cost=False):
        order = [F.col(c).desc() for c in ("gain", "weight", "site_id")]
        found = self.gains() if most_cost is None else self.gains().where(F.col("cost") <= most_cost)
        top = found.orderBy(*([(F.col("gain") / F.col("cost")).desc()] if per_cost else []), *order).first()
        return None if top is None else (top["site_id"], top["gain"], top["cost"])

    def serve(self, site: int) -> None:
        """With capacities only the paths that the site has room for get its score: the largest gains first, ties by
        the lowest path. Else what is served follows from the open sites."""
        if not self.spec.capacity:
            return
        room = self.sites.where(F.col("site_id") == site).first()["room"]
        rows = self.over_best(self.rows_of([site])).where("gain > 0")
        if room is not None:
            rows = rows.withColumn("rank", F.row_number().over(Window.partitionBy("site_id").orderBy(F.col("gain").desc(), "path_id"))).where(F.col("rank") <= room)
        fresh = rows.select("path_id", F.col("score").alias("u"))
        before = self.served if self.served is not None else fresh.limit(0)
        self.served = materialize(before.unionByName(fresh).groupBy("path_id").agg(F.max("u").alias("u")), "served")

    def delta(self) -> Placement:
        """One number a site on the driver; after each pick only the paths that gained send corrections to their sites."""
        self.start()
        rows = {r["site_id"]: [r["gain"], r["weight"]] for r in self.gains().toLocalIterator()}
        while len(self.chosen) < self.spec.k and rows:
            site = max(rows, key=lambda s: (rows[s][0], rows[s][1], s))
            gain = rows.pop(site)[0]
            if gain and len(self.chosen) + 1 < self.spec.k:
                moved = self.over_best(self.rows_of([site])).where("gain > 0").select("path_id", F.col("score").alias("after"), (F.col("score") - F.col("gain")).alias("before"))
                drop = F.greatest(F.col("score") - F.col("before"), F.lit(0)) - F.greatest(F.col("score") - F.col("after"), F.lit(0))
                changes = self.by_path.join(moved, "path_id").groupBy("site_id").agg(F.sum(drop).alias("drop")).where(F.col("drop") > 0)
                for r in changes.toLocalIterator():
                    if r["site_id"] in rows:
                        rows[r["site_id"]][0] -= r["drop"]
            self.take(site, gain)
        return self.out

    def lazy(self, batch: int = 8) -> Placement:
        """Old gains bound new ones, as gains never grow: only the leaders are evaluated anew, a few at a time."""
        self.start()
        heap = [(-r["gain"], -r["weight"], -r["site_id"], 0) for r in self.gains().toLocalIterator()]
        heapq.heapify(heap)
        while len(self.chosen) < self.spec.k and heap:
            now = len(self.chosen)
            if heap[0][3] == now:
                g, _, s, _ = heapq.heappop(heap)
                self.take(-s, -g)
                continue
            stale = []
            while heap and heap[0][3] != now and len(stale) < batch:
                stale.append(heapq.heappop(heap))
            ids = [-s for _, _, s, _ in stale]
            fresh = {r["site_id"]: r["gain"] for r in self.over_best(self.rows_of(ids)).groupBy("site_id").agg(F.sum("gain").alias("gain")).collect()}
            self.out.evaluations += len(ids)
            for _, w, s, _ in stale:
                heapq.heappush(heap, (-fresh.get(-s, 0), w, s, now))
        return self.out


def attributes(sites: DataFrame) -> DataFrame:
    """(site_id, cost, room): a missing cost is 1, a missing or null capacity no limit."""
    cost = F.col("cost").cast("double") if "cost" in sites.columns else F.lit(1.0)
    room = F.col("capacity").cast("long") if "capacity" in sites.columns else F.lit(None).cast("long")
    return sites.select(F.col("site_id").cast("long").alias("site_id"), cost.alias("cost"), room.alias("room"))


def place_inconvenience(detour: DataFrame, k: int, n_paths: int, sites: DataFrame | None = None) -> tuple[Placement, DataFrame]:
    """Least total detour. An empty set has no finite total, so every path starts just above its largest detour; the
    scores are what a site saves of that, and the last column of the frame is the total detour left. A path that cannot
    reach some site has no detour to it, so there is no total: that is an error."""
    spark = detour.sparkSession
    pairs = detour.groupBy("path_id").agg((F.max("metres") + 1).alias("worst"), F.count("*").alias("reached"))
    candidates = (sites if sites is not None else detour).select("site_id").distinct().count()
    held, total, least = pairs.agg(F.count("*"), F.coalesce(F.sum("worst"), F.lit(0)), F.min("reached")).first()
    if held != n_paths or (held and least < candidates):
        raise ValueError("every path must reach every site: the total detour is not defined else")
    cover = detour.join(pairs.select("path_id", "worst"), "path_id").select("path_id", "site_id", (F.col("worst") - F.col("metres")).alias("score"))
    placed = greedy_place(cover, PlacementSpec(k=k, mode="auto"), n_paths, sites)
    frame = spark.createDataFrame([(s, i, g, int(total) - u) for s, i, g, u in placed.steps], "step int, site_id long, gain long, total_metres long")
    return placed, frame


def continue_placement(cover: DataFrame, before: Placement, k: int, n_paths: int) -> Placement:
    """Further picks after a saved placement: they depend only on the set that is open."""
    more = greedy_place(cover, PlacementSpec(k=k - len(before.steps), existing=tuple(before.sites)), n_paths)
    steps = [*before.steps, *((len(before.steps) + s, i, g, u) for s, i, g, u in more.steps)]
    return replace(before, steps=steps)


def utility_of(cover: DataFrame, chosen: list[int]) -> int:
    """Total score of the paths over the chosen sites."""
    best = cover.where(F.col("site_id").isin(chosen) if chosen else F.lit(False)).groupBy("path_id").agg(F.max("score").alias("u"))
    return int(best.agg(F.coalesce(F.sum("u"), F.lit(0))).first()[0])


def prefix_utilities(cover: DataFrame, chosen: list[int]) -> list[int]:
    """Total score of the paths over the first one, two, ... of the chosen sites, from one pass over their rows."""
    if not chosen:
        return []
    own = [F.coalesce(F.max(F.when(F.col("site_id") == s, F.col("score"))), F.lit(0)) for s in chosen]
    each = cover.where(F.col("site_id").isin(list(chosen))).groupBy("path_id").agg(F.array(*own).alias("own"))
    best = [F.coalesce(F.sum(F.array_max(F.slice("own", 1, k))), F.lit(0)) for k in range(1, len(chosen) + 1)]
    return [int(x) for x in each.agg(F.array(*best).alias("u")).first()["u"]]


def served_by(cover: DataFrame, chosen: list[int], sites: DataFrame) -> int:
    """Total score when the chosen sites open one after the other and each serves its largest gains, up to its capacity."""
    loop = _FrameLoop(cover, PlacementSpec(k=len(chosen), capacity=True), 0, sites)
    try:
        for site in chosen:
            loop.serve(site)
        return int(loop.best_so_far().agg(F.coalesce(F.sum("u"), F.lit(0))).first()[0]) if chosen else 0
    finally:
        loop.close()


def seeded_order(column: Column, seed: int) -> Column:
    """An order that looks random and that any engine can repeat."""
    return F.md5(F.concat(F.lit(f"{seed}:"), column.cast("string")))
