"""Paths: trips from events and orders, gap filling, users' unions, static users, map matching."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from waysite.operators.distance import MOST_BROADCAST_EDGES, Roads
from waysite.sources.tables import materialize


def event_visits(events: DataFrame) -> DataFrame:
    """events -> (user_id, ts, event_id, node_id): the node is the number k of the JSON properties."""
    return events.select("user_id", "ts", "event_id", F.get_json_object("props", "$.k").cast("long").alias("node_id")).where(F.col("node_id").isNotNull())


def numbered(visits: DataFrame, path: Column, *order: str) -> DataFrame:
    """Visits numbered along their path."""
    w = Window.partitionBy("path_id").orderBy(*order)
    return visits.withColumn("path_id", path.cast("long")).select("path_id", (F.row_number().over(w) - 1).alias("seq"), "node_id", "ts")


def day_trip() -> Column:
    """The path_id of a visit by its user and day: user_id * 100 + day number."""
    return (F.col("user_id") * 100 + F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date"))).cast("long")


def trips_by_day(events: DataFrame) -> DataFrame:
    """A trip is what a user visits on one day."""
    return numbered(event_visits(events), day_trip(), "ts", "event_id")


def trips_by_session(events: DataFrame, gap_seconds: int = 6 * 3600) -> DataFrame:
    """A trip ends where the user pauses for longer than the gap: path_id = user_id * 10000 + number of the trip."""
    by_user = Window.partitionBy("user_id").orderBy("ts", "event_id")
    seconds = F.unix_timestamp("ts")
    opened = event_visits(events).withColumn("new", F.coalesce((seconds - F.lag(seconds).over(by_user) > gap_seconds).cast("int"), F.lit(0)))
    session = opened.withColumn("trip", F.sum("new").over(by_user.rowsBetween(Window.unboundedPreceding, 0)))
    return numbered(session, F.col("user_id") * 10000 + F.col("trip"), "ts", "event_id")


def order_paths(lineitem: DataFrame, key: str = "l_suppkey", n: int | None = None) -> DataFrame:
    """An order visits the nodes of its line items in shipping order; keys start at 1, nodes at 0."""
    node = F.col(key) - 1 if n is None else F.pmod(F.col(key) - 1, F.lit(n))
    visits = lineitem.select("l_orderkey", F.col("l_shipdate").alias("ts"), "l_linenumber", "l_suppkey", "l_partkey", node.cast("long").alias("node_id"))
    return numbered(visits, F.col("l_orderkey"), "ts", "l_linenumber", "l_suppkey", "l_partkey")


def union_paths_by_owner(points: DataFrame, owner: Column) -> DataFrame:
    """A user with several paths is served on any of them: one path of all their points, in the order of the paths."""
    w = Window.partitionBy("owner").orderBy("path_id", "seq")
    return points.withColumn("owner", owner.cast("long")).select(F.col("owner").alias("path_id"), (F.row_number().over(w) - 1).alias("seq"), "node_id", "ts")


def static_paths(users: DataFrame, user: str, node: Column) -> DataFrame:
    """Users who stay at one node."""
    return users.select(F.col(user).cast("long").alias("path_id"), F.lit(0).alias("seq"), node.cast("long").alias("node_id"), F.lit(None).cast("timestamp").alias("ts"))


def fill_gaps(points: DataFrame, side: int | None = None, rule: str = "x_then_y", edges: DataFrame | None = None) -> DataFrame:
    """Nodes between two visits: on the lattice of a side along x first, then along y; on any network ("shortest", with its
    edges) along a shortest way, of which each next node is the smallest possible; "none" leaves the visits.

    Stands in for map matching on test data; each visit but the first brings the nodes of its approach with it. A visit
    that can't be reached from the one before it follows that one directly."""
    if rule == "none":
        return points
    if rule == "shortest":
        return fill_shortest(points, edges)
    if rule != "x_then_y":
        raise ValueError(f"unknown rule {rule}")
    w = Window.partitionBy("path_id").orderBy("seq")
    before = F.lag("node_id").over(w)
    x, y = F.pmod(F.col("node_id"), F.lit(side)), F.floor(F.col("node_id") / side)
    with_last = points.withColumn("last", before).withColumn("x0", F.pmod(F.col("last"), F.lit(side))).withColumn("y0", F.floor(F.col("last") / side)).withColumn("x1", x).withColumn("y1", y)
    along_x = F.expr(f"CASE WHEN x0 = x1 THEN cast(array() as array<bigint>) ELSE transform(sequence(x0 + cast(sign(x1 - x0) as int), x1), v -> cast(y0 * {side} + v AS bigint)) END")
    along_y = F.expr(f"CASE WHEN y0 = y1 THEN cast(array() as array<bigint>) ELSE transform(sequence(y0 + cast(sign(y1 - y0) as int), y1), v -> cast(v * {side} + x1 AS bigint)) END")
    steps = F.when(F.col("last").isNull() | (F.col("last") == F.col("node_id")), F.array("node_id")).otherwise(F.concat(along_x, along_y))
    walked = with_last.withColumn("x0", F.col("x0").cast("int")).withColumn("x1", F.col("x1").cast("int")).withColumn("y0", F.col("y0").cast("int")).withColumn("y1", F.col("y1").cast("int")).select("path_id", "seq", "ts", F.posexplode(steps).alias("sub", "node"))
    order = Window.partitionBy("path_id").orderBy("seq", "sub")
    return walked.select("path_id", (F.row_number().over(order) - 1).alias("seq"), F.col("node").cast("long").alias("node_id"), "ts")


def fill_shortest(points: DataFrame, edges: DataFrame) -> DataFrame:
    w = Window.partitionBy("path_id").orderBy("seq")
    lagged = points.withColumn("last", F.lag("node_id").over(w))
    ways = materialize(shortest_ways(edges, lagged.where("last <> node_id").select(F.col("last").alias("src"), F.col("node_id").alias("dst"))), "ways")
    known = lagged.join(ways, (F.col("last") == F.col("src")) & (F.col("node_id") == F.col("dst")), "left")
    steps = F.coalesce("way", F.array("node_id"))
    walked = known.select("path_id", "seq", "ts", F.posexplode(steps).alias("sub", "node"))
    order = Window.partitionBy("path_id").orderBy("seq", "sub")
    return walked.select("path_id", (F.row_number().over(order) - 1).alias("seq"), F.col("node").alias("node_id"), "ts")


def shortest_ways(edges: DataFrame, pairs: DataFrame) -> DataFrame:
    """pairs(src, dst) -> (src, dst, way): the nodes of a shortest way after src; each next node is the smallest on any
    shortest way. One search against the roads from each end, for all its starts; the edges are broadcast (checked)."""
    if edges.limit(MOST_BROADCAST_EDGES + 1).count() > MOST_BROADCAST_EDGES:
        raise ValueError("too many roads to broadcast")
    flipped = edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "metres")
    shared = edges.sparkSession.sparkContext.broadcast((Roads.of(edges), Roads.of(flipped)))

    def search(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        roads, back = shared.value
        reach = back.search()
        for frame in frames:
            out = []
            for end, starts in zip(frame["dst"], frame["starts"], strict=True):
                left = dict(zip(*(list(x) for x in reach(int(end), float("inf"), set(map(int, starts)))), strict=True))
                for start in map(int, starts):
                    at, way = start, []
                    while at in left and at != end:
                        i = int(np.searchsorted(roads.ids, at))
                        a, b = roads.start[i], roads.start[i + 1]
                        at = min(int(n) for n, m in zip(roads.ids[roads.to[a:b]], roads.metres[a:b], strict=True) if int(n) in left and left[int(n)] + m == left[at])
                        way.append(at)
                    if way:
                        out.append((start, int(end), way))
            yield pd.DataFrame(out, columns=["src", "dst", "way"])

    ends = pairs.groupBy(F.col("dst").cast("long").alias("dst")).agg(F.collect_set(F.col("src").cast("long")).alias("starts"))  # at most all nodes
    return ends.mapInPandas(search, "src long, dst long, way array<long>")


def path_arrays(points: DataFrame) -> DataFrame:
    """(path_id, nodes): a path's node ids in order."""
    gathered = points.groupBy("path_id").agg(F.array_sort(F.collect_list(F.struct("seq", "node_id"))).alias("steps"))
    return gathered.select("path_id", F.transform("steps", lambda s: s["node_id"]).alias("nodes"))


def raw_points(events: DataFrame) -> DataFrame:
    """Noisy positions of event visits, for map matching: the node's place on the 10 x 10 lattice, 100 m apart, moved
    by up to 20 m."""
    v = event_visits(events)
    return v.select("user_id", "ts", "event_id", (100 * F.pmod("node_id", F.lit(10)) + F.pmod(7 * F.col("event_id"), F.lit(41)) - 20).cast("double").alias("px"), (100 * F.floor(F.col("node_id") / 10) + F.pmod(11 * F.col("event_id"), F.lit(41)) - 20).cast("double").alias("py"), F.col("node_id").alias("true_node"))


def map_match(points: DataFrame, nodes: DataFrame, key: str, spacing: float = 100.0) -> DataFrame:
    """Nearest node of each point: cells of one spacing; a point meets the nodes of the 3 x 3 cells around it.

    points: px, py and the key column; nodes: node_id, x, y in units of spacing. Ties go to the smaller node id."""
    grid = F.array(*(F.lit(d) for d in (-1, 0, 1)))
    placed = nodes.select("node_id", (F.col("x") * spacing).alias("nx"), (F.col("y") * spacing).alias("ny")).withColumn("cx", F.floor(F.col("nx") / spacing)).withColumn("cy", F.floor(F.col("ny") / spacing))
    spread = placed.withColumn("dx", F.explode(grid)).withColumn("dy", F.explode(grid)).select("node_id", "nx", "ny", (F.col("cx") + F.col("dx")).alias("gx"), (F.col("cy") + F.col("dy")).alias("gy"))
    celled = points.withColumn("gx", F.floor(F.col("px") / spacing)).withColumn("gy", F.floor(F.col("py") / spacing))
    square = F.pow(F.col("px") - F.col("nx"), 2) + F.pow(F.col("py") - F.col("ny"), 2)
    return celled.join(spread, ["gx", "gy"]).groupBy(key).agg(F.min_by("node_id", F.struct(square.alias("d"), "node_id")).alias("node_id"))
