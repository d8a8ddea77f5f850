"""Road networks: lattices and other shapes over given ids, and sites in the middle of a road."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Network:
    nodes: DataFrame  # node_id, x, y
    edges: DataFrame  # src, dst, metres


def edge_metres(src, dst):
    """A positive length that differs by direction."""
    return (F.lit(100) + F.pmod(31 * src + 17 * dst, F.lit(50))).cast("int")


def lattice_nodes(ids: DataFrame, n: int) -> DataFrame:
    """ids(node_id) 0..n-1 on a square of side ceil(sqrt(n))."""
    side = math.isqrt(max(n - 1, 0)) + 1
    return ids.select(F.col("node_id").cast("long").alias("node_id"), F.pmod("node_id", F.lit(side)).cast("int").alias("x"), F.floor(F.col("node_id") / side).cast("int").alias("y"))


def build_network(ids: DataFrame, n: int, shape: str = "mesh") -> Network:
    """Edges by shape. mesh: the sides of the lattice; star: node 0 joined to nine spokes of eleven nodes in a row;
    poly: four quarters of the lattice joined by roads between their middles. Every road has both directions."""
    nodes = lattice_nodes(ids, n)
    side = math.isqrt(max(n - 1, 0)) + 1
    node = F.col("node_id")
    east = (F.col("x") < side - 1) & (node + 1 < n)
    south = node + side < n
    if shape == "mesh":
        roads = _roads(nodes, [(node + 1, east), (node + side, south)])
    elif shape == "star":
        spoke = F.floor((node - 1) / 11)
        inner = (node > 0) & (F.pmod(node - 1, F.lit(11)) < 10) & (node + 1 < n) & (F.floor(node / 11) == spoke)
        heads = (node > 0) & (F.pmod(node - 1, F.lit(11)) == 0)
        roads = _roads(nodes, [(node + 1, inner)]).unionByName(nodes.where(heads).select(F.lit(0).cast("long").alias("src"), node.alias("dst")))
    elif shape == "poly":
        half = side // 2
        within = lambda c: F.col(c) != half - 1
        hub = half // 2 * side + half // 2
        hubs = [hub, hub + half, hub + half * side, hub + half * side + half]
        express = [(a, b) for i, a in enumerate(hubs) for b in hubs[i + 1 :] if b < n]
        roads = _roads(nodes, [(node + 1, east & within("x")), (node + side, south & within("y"))])
        if express:
            roads = roads.unionByName(ids.sparkSession.createDataFrame(express, "src long, dst long"))
    else:
        raise ValueError(f"unknown shape {shape}")
    both = roads.unionByName(roads.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    return Network(nodes, both.select("src", "dst", edge_metres(F.col("src"), F.col("dst")).alias("metres")))


def _roads(nodes: DataFrame, rules: list) -> DataFrame:
    parts = [nodes.where(when).select(F.col("node_id").alias("src"), to.cast("long").alias("dst")) for to, when in rules]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def id_range(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(0, n, 1, 4).withColumnRenamed("id", "node_id")


def split_edge(net: Network, src: int, dst: int, at_metres: int, new_id: int) -> Network:
    """A site in mid-road becomes a node: the road src-dst goes in each direction it has, and two parts replace it.

    at_metres: from src along src->dst; the other direction is cut in proportion, to whole metres, both parts at least 1."""
    here = (F.col("src") == src) & (F.col("dst") == dst)
    back = (F.col("src") == dst) & (F.col("dst") == src)
    cut = net.edges.where(here | back)
    length = net.edges.where(here).agg(F.max("metres")).first()[0]
    if length is None or not 0 < at_metres < length:
        raise ValueError("no such road, or the place is not inside it")
    share = F.greatest(F.lit(1), F.least(F.col("metres") - 1, F.round(F.col("metres") * at_metres / length).cast("int")))
    near = F.when(here, share).otherwise(F.col("metres") - share)
    halves = cut.select(F.col("src"), F.lit(new_id).cast("long").alias("dst"), near.cast("int").alias("metres")).unionByName(cut.select(F.lit(new_id).cast("long").alias("src"), F.col("dst"), (F.col("metres") - near).cast("int").alias("metres")))
    ends = net.nodes.where(F.col("node_id").isin(src, dst)).agg(F.avg("x").cast("int").alias("x"), F.avg("y").cast("int").alias("y"))
    nodes = net.nodes.unionByName(ends.select(F.lit(new_id).cast("long").alias("node_id"), "x", "y"))
    return Network(nodes, net.edges.where(~(here | back)).unionByName(halves))
