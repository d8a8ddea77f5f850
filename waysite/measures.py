"""Measures of answers, times, sizes and bounds."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from waysite.functions.preference import MICRO
from waysite.operators.index import Index


def utility_pct(utility: int, n_paths: int) -> float:
    return utility / MICRO / n_paths * 100 if n_paths else 0.0


def relative_loss(reference: float, value: float) -> float:
    return (reference - value) / reference if reference else 0.0


def speed_up(reference_s: float, value_s: float) -> float:
    return reference_s / value_s if value_s else math.inf


def optimality_ratio(value: float, optimum: float) -> float:
    return value / optimum if optimum else 1.0


def timed(f: Callable, *args, **options) -> tuple[object, float]:
    began = time.perf_counter()
    out = f(*args, **options)
    return out, time.perf_counter() - began


def file_bytes(df: DataFrame) -> int:
    """Bytes of the files behind a table that was written."""
    spark = df.sparkSession
    total = 0
    for name in df.inputFiles():
        path = spark._jvm.org.apache.hadoop.fs.Path(name)
        total += path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(path).getLen()
    return total


def index_rows(index: Index) -> DataFrame:
    """(level, rows) over all relations of the index; a path that stands for several has as many rows."""
    out = None
    for p in (index.member, index.link, index.path):
        if p is index.path and index.times is not None:
            one = p.join(index.times, "path_id").groupBy("level").agg(F.sum("times").alias("rows"))
        else:
            one = p.groupBy("level").agg(F.count("*").alias("rows"))
        out = one if out is None else out.unionByName(one)
    return out.groupBy("level").agg(F.sum("rows").alias("rows"))


def index_bytes(index: Index) -> int:
    """Bytes of the files of all relations of the index."""
    return sum(file_bytes(p) for p in (index.member, index.link, index.path, index.sites, index.clusters()))


def estimate_error(estimated: DataFrame, true: DataFrame) -> DataFrame:
    """Metres by which estimates exceed true detours, as (n, mean_excess, least_excess)."""
    t = true.select(F.col("path_id").alias("p"), F.col("site_id").alias("s"), F.col("metres").alias("true"))
    both = estimated.join(t, (F.col("path_id") == F.col("p")) & (F.col("site_id") == F.col("s")))
    return both.agg(F.count("*").alias("n"), F.round(F.avg(F.col("metres") - F.col("true")), 6).alias("mean_excess"), F.min(F.col("metres") - F.col("true")).alias("least_excess"))


def sites_within(trips: DataFrame, tau: float) -> DataFrame:
    """Mean number of other sites within a round trip of tau."""
    near = trips.where(F.col("a") != F.col("b")).groupBy("a").agg(F.sum((F.col("metres") <= tau).cast("long")).alias("n"))
    return near.agg(F.round(F.avg("n"), 6).alias("mean_sites"))


def compression(points: DataFrame, compressed: DataFrame) -> DataFrame:
    """(level, points, steps): path points against steps of the compressed paths."""
    n = points.count()
    return compressed.groupBy("level").agg(F.count("*").alias("steps")).withColumn("points", F.lit(n).cast("long")).select("level", "points", "steps")


def guarantee(kind: str, **v: float) -> float:
    """Lower bounds as fractions of the optimum (quota: an upper bound on the number of sites against the least)."""
    if kind == "greedy":
        return max(1 - 1 / math.e, v["k"] / v["n"])
    if kind == "index":
        return v.get("preference_at_tau", 1.0) * v["k"] / v["clusters"]
    if kind == "budget":
        return (1 - 1 / math.e) / 2
    if kind in ("quota", "clusters"):
        return 1 + math.log(v["n"])
    if kind == "sketch":
        return (1 - v["error"]) ** v["k"]
    raise ValueError(f"unknown kind {kind}")
