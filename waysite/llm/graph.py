"""Connected components over DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, materialize


def connected_components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """links(a, b) -> (node, root): root is the smallest node of the component; nodes without links don't occur.

    Alternates two star operations until nothing changes: a node hands its larger neighbours to its smallest neighbour,
    then itself and its smaller neighbours. Neighbourhoods are reduced to minima before they are shuffled, and every
    round is written to the shared folder."""
    pairs = links.where("a <> b").select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")).distinct()
    pairs = materialize(pairs, "cc-links")
    before = None
    for _ in range(most_rounds):
        moved, least = large_star(pairs)
        last, pairs = pairs, materialize(small_star(moved), "cc-round")
        discard(last, least)
        now = tuple(pairs.agg(F.count("*"), F.sum(F.xxhash64("hi", "lo").cast("decimal(38,0)"))).first())
        if now == before:
            break
        before = now
    else:
        raise RuntimeError("components did not settle")
    return pairs.select(F.col("hi").alias("node"), F.col("lo").alias("root")).unionByName(pairs.select(F.col("lo").alias("node"), F.col("lo").alias("root")).distinct())


def large_star(pairs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The links after the step, and the table it reads."""
    both = pairs.select(F.col("hi").alias("u"), F.col("lo").alias("v")).unionByName(pairs.select(F.col("lo").alias("u"), F.col("hi").alias("v")))
    # Written, so that the join stands between two shuffles and the neighbours of a hub can be split over tasks.
    least = materialize(both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("w"), F.least("u", "m").alias("m")), "cc-least")
    larger = pairs.select(F.col("lo").alias("u"), F.col("hi").alias("v"))
    return larger.join(least, F.col("u") == F.col("w")).where("v <> m").select(F.col("v").alias("hi"), F.col("m").alias("lo")).distinct(), least


def small_star(pairs: DataFrame) -> DataFrame:
    least = pairs.groupBy("hi").agg(F.min("lo").alias("m")).select(F.col("hi").alias("w"), "m")
    joined = pairs.join(least, F.col("hi") == F.col("w"))
    moved = joined.where("lo <> m").select(F.col("lo").alias("hi"), F.col("m").alias("lo"))
    return moved.unionByName(least.select(F.col("w").alias("hi"), F.col("m").alias("lo"))).distinct()
