"""Networks, paths and covers made from the given tables, each written once a session and folder."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from waysite.functions import preference as pref
from waysite.operators import detours as dt
from waysite.operators import index as ix
from waysite.operators import network as nw
from waysite.operators import packed as pk
from waysite.operators import paths as pt
from waysite.operators.distance import network_distances, round_trip
from waysite.sources.tables import materialize, read_table

#: Defaults of the workloads.
TAU, K, EPS, COPIES = 400, 5, 0.75, 30
_held: dict[tuple, object] = {}


def once(spark: SparkSession, sf_dir: str, name: str, make: Callable):
    """A relation (or index) made once for a session and a folder of tables; relations are written to the shared folder."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _held:
        made = make()
        _held[key] = materialize(made, name) if isinstance(made, DataFrame) else made
    return _held[key]


def forget() -> None:
    _held.clear()


@dataclass(frozen=True)
class World:
    """One workload: a network, its distances, paths on it and candidate sites."""

    spark: SparkSession
    sf_dir: str
    name: str
    n: int
    points_of: Callable[[], DataFrame]
    shape: str = "mesh"
    times_of: Callable[[], DataFrame] | None = None

    @property
    def side(self) -> int:
        return math.isqrt(max(self.n - 1, 0)) + 1

    def net(self) -> nw.Network:
        return nw.build_network(nw.id_range(self.spark, self.n), self.n, self.shape)

    def given_net(self, ids: Callable[[], DataFrame]) -> nw.Network:
        """The network over the different node ids of a given table, which is read each time."""
        held = materialize(ids().where("node_id IS NOT NULL").select(F.col("node_id").cast("long").alias("node_id")).distinct(), "given-ids")
        return nw.build_network(held, held.count(), self.shape)

    def dist(self) -> DataFrame:
        return once(self.spark, self.sf_dir, f"dist-{self.shape}-{self.n}", lambda: network_distances(self.net().edges, self.net().nodes))

    def trips(self) -> DataFrame:
        return once(self.spark, self.sf_dir, f"trips-{self.shape}-{self.n}", lambda: round_trip(self.dist()))

    def points(self) -> DataFrame:
        return once(self.spark, self.sf_dir, f"points-{self.name}", self.points_of)

    def times(self) -> DataFrame | None:
        """(path_id, times): how many paths each path stands for, if paths stand for several."""
        return None if self.times_of is None else self.times_of()

    def n_paths(self) -> int:
        if self.times_of is not None:
            return once(self.spark, self.sf_dir, f"m-{self.name}", lambda: int(self.times().agg(F.coalesce(F.sum("times"), F.lit(0))).first()[0]))
        return once(self.spark, self.sf_dir, f"m-{self.name}", lambda: self.points().select("path_id").distinct().count())

    def routes(self) -> DataFrame:
        """(route, nodes, times): paths of equal sets of nodes as one, named by the least of them."""
        return once(self.spark, self.sf_dir, f"routes-{self.name}", lambda: dt.counted_routes(self.points()))

    def route_of(self) -> DataFrame:
        """(path_id, route) of every path."""
        return once(self.spark, self.sf_dir, f"route-of-{self.name}", lambda: dt.route_arrays(self.points()).join(self.routes().select("nodes", "route"), "nodes").select("path_id", "route"))

    def by_routes(self) -> World:
        """The same workload with each route as one path. Detours "any" follow from a path's nodes, so the paths of a route
        are covered alike: scores are multiplied by their number, and every sum over paths stays what it is."""
        points = lambda: dt.route_points(self.routes())
        times = lambda: self.routes().select(F.col("route").alias("path_id"), "times")
        return World(self.spark, self.sf_dir, f"{self.name}-routes", self.n, points, self.shape, times)

    def sites(self) -> DataFrame:
        return nw.id_range(self.spark, self.n).withColumnRenamed("node_id", "site_id")

    def detours(self, pair: str = "any") -> DataFrame:
        kernel = pair == "any" and self.n <= dt.MOST_KERNEL_NODES
        make = (lambda: dt.kernel_detours(self.points(), self.sites(), self.dist())) if kernel else (lambda: dt.detours(self.points(), self.sites(), self.dist(), pair))
        return once(self.spark, self.sf_dir, f"detour-{self.shape}-{self.name}-{pair}", make)

    def cover(self, preference: pref.Preference) -> DataFrame:
        return dt.times_over(dt.cover(self.detours(), preference), self.times())

    def index(self, eps: float = EPS, rule: str = "closest") -> ix.Index:
        return once(self.spark, self.sf_dir, f"index-{self.shape}-{self.name}-{eps}-{rule}", lambda: replace(ix.build_index(self.points(), self.sites(), self.dist(), self.trips(), eps, rule, kernel=self.n <= dt.MOST_KERNEL_NODES), times=self.times()))

    def bounded_index(self, limits: tuple[int, int], eps: float = EPS) -> ix.Index:
        """An index whose searches end where its largest threshold does; nothing needs all distances."""
        return once(self.spark, self.sf_dir, f"bounded-{self.shape}-{self.name}-{limits}-{eps}", lambda: ix.build_index_bounded(self.points(), self.sites(), self.net().edges, self.net().nodes, limits, eps))

    def packed_cover(self, tau: int, largest: int) -> pk.PackedCover:
        """The binary cover as bits, made from all distances between the nodes, which are found once for all thresholds up to
        the largest."""
        ways = once(self.spark, self.sf_dir, f"ways-{self.shape}-{self.n}-{largest}", lambda: self.spark.sparkContext.broadcast(pk.Ways.of(self.net().edges, self.net().nodes, largest)))
        return pk.near_cover(self.points(), ways, tau)

    def near_cover(self, tau: int) -> DataFrame:
        """The binary cover; on networks without a distance matrix by searches made for it."""
        if self.n <= dt.MOST_KERNEL_NODES:
            return once(self.spark, self.sf_dir, f"near-{self.shape}-{self.name}-{tau}", lambda: dt.cover(dt.kernel_detours(self.points(), self.sites(), self.dist(), tau), pref.binary(tau)))
        return once(self.spark, self.sf_dir, f"near-{self.shape}-{self.name}-{tau}", lambda: dt.cover_at_query(self.net().edges, self.points(), self.sites(), tau, pref.binary(tau)))


def net100(spark: SparkSession, sf_dir: str, filled: bool = False, shape: str = "mesh") -> World:
    events = lambda: read_table(spark, sf_dir, "events", "user_id", "ts", "event_id", "props")
    raw = lambda: pt.trips_by_day(events())
    return World(spark, sf_dir, "net100-filled" if filled else "net100", 100, (lambda: pt.fill_gaps(raw(), 10)) if filled else raw, shape)


def visited_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(node_id): the nodes that events visit."""
    return pt.event_visits(read_table(spark, sf_dir, "events", "user_id", "ts", "event_id", "props")).select("node_id")


def home_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(node_id): the nations that customers live in."""
    return read_table(spark, sf_dir, "customer", "c_nationkey").select(F.col("c_nationkey").alias("node_id"))


def net100u(spark: SparkSession, sf_dir: str) -> World:
    base = net100(spark, sf_dir)
    return World(spark, sf_dir, "net100u", 100, lambda: pt.union_paths_by_owner(base.points(), F.floor(F.col("path_id") / 100)))


def order_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_table(spark, sf_dir, "lineitem", "l_orderkey", "l_shipdate", "l_linenumber", "l_suppkey", "l_partkey")


def net25(spark: SparkSession, sf_dir: str) -> World:
    def points() -> DataFrame:
        supplier = read_table(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey")
        lines = order_lines(spark, sf_dir).join(supplier, F.col("l_suppkey") == F.col("s_suppkey"))
        visits = lines.select("l_orderkey", F.col("l_shipdate").alias("ts"), "l_linenumber", "l_suppkey", "l_partkey", F.col("s_nationkey").cast("long").alias("node_id"))
        return pt.numbered(visits, F.col("l_orderkey"), "ts", "l_linenumber", "l_suppkey", "l_partkey")

    return World(spark, sf_dir, "net25", 25, points)


def keyed_world(spark: SparkSession, sf_dir: str, table: str, key: str, line_key: str, name: str, filled: bool) -> World:
    n = once(spark, sf_dir, f"n-{table}", lambda: read_table(spark, sf_dir, table, key).count())
    side = math.isqrt(max(n - 1, 0)) + 1
    raw = lambda: pt.order_paths(order_lines(spark, sf_dir), line_key)
    return World(spark, sf_dir, name + ("-filled" if filled else ""), n, (lambda: pt.fill_gaps(raw(), side)) if filled else raw)


def netsup(spark: SparkSession, sf_dir: str, filled: bool = True) -> World:
    return keyed_world(spark, sf_dir, "supplier", "s_suppkey", "l_suppkey", "netsup", filled)


def netpart(spark: SparkSession, sf_dir: str, filled: bool = False) -> World:
    return keyed_world(spark, sf_dir, "part", "p_partkey", "l_partkey", "netpart", filled)


def static100(spark: SparkSession, sf_dir: str) -> World:
    return World(spark, sf_dir, "static100", 100, lambda: pt.static_paths(read_table(spark, sf_dir, "customer", "c_custkey"), "c_custkey", F.pmod("c_custkey", F.lit(100))))


# -- site attributes: a hash that both engines compute alike stands for the normal variable

_P = 2_147_483_647


def hash_normal(ids, copies: int = 12):
    """About standard normal: the sum of twelve uniform hashes of the id, less six."""
    total = F.lit(0).cast("long")
    for c in range(copies):
        total = total + F.pmod(F.lit(pow(48271, c + 1, _P)).cast("long") * (ids.cast("long") + 1) + F.lit(pow(16807, c + 1, _P)).cast("long"), F.lit(_P))
    return total.cast("double") / F.lit(float(_P)) - copies / 2


def with_costs(sites: DataFrame, sigma: float) -> DataFrame:
    """Costs of mean 1 and the given spread, never below 0.1, in ten-thousandths."""
    return sites.withColumn("cost", F.round(F.greatest(F.lit(0.1), 1 + sigma * hash_normal(F.col("site_id"))), 4))


def with_capacities(sites: DataFrame, mean: float) -> DataFrame:
    """Capacities of the given mean and a tenth of it as spread, whole and never below 0."""
    return sites.withColumn("capacity", F.greatest(F.lit(0), F.round(mean * (1 + 0.1 * hash_normal(F.col("site_id"))))).cast("long"))
