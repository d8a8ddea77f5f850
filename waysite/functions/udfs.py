"""User-defined twins of built-in expressions, for functions given in Python; the built-ins stay the default."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from waysite.functions.preference import MICRO
from waysite.operators.detours import FAR, Matrix
from waysite.operators.sketch import hashed, position


def scored(preference: Callable[[pd.Series], pd.Series]):
    """A preference over whole columns of metres, as a score in millionths."""

    @F.pandas_udf("long")
    def score(metres: pd.Series) -> pd.Series:
        return (preference(metres.astype(float)) * MICRO).round().astype("int64")

    return score


def fm_words_by_udf(spark: SparkSession, cover: DataFrame, f: int) -> DataFrame:
    """Sketch words by a grouped-aggregate pandas function: the twin of bit_or."""

    @F.pandas_udf("long")
    def any_bit(bits: pd.Series) -> int:
        out = 0
        for b in bits.unique():
            out |= int(b)
        return out

    copies = cover.select("site_id", "path_id").withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(f - 1))))
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), position(hashed(F.col("path_id"), F.col("copy"), f)).cast("int"))
    return copies.select("site_id", "copy", bit.alias("bit")).groupBy("site_id", "copy").agg(any_bit("bit").alias("word"))


@F.udtf(returnType="node_id: bigint")
class LatticeSteps:
    """The lattice nodes from one node (left out) to another, along x first; from null: the node alone."""

    def eval(self, last: int, node: int, side: int) -> Iterator[tuple[int]]:
        if last is None or last == node:
            yield (node,)
            return
        x, y, x1, y1 = last % side, last // side, node % side, node // side
        while x != x1:
            x += 1 if x1 > x else -1
            yield (y * side + x,)
        while y != y1:
            y += 1 if y1 > y else -1
            yield (y * side + x1,)


def fill_by_udtf(spark: SparkSession, points: DataFrame, side: int) -> DataFrame:
    """Gap filling by a Python table function: the twin of fill_gaps()."""
    spark.udtf.register("lattice_steps", LatticeSteps)
    points.createOrReplaceTempView("points_to_fill")
    return spark.sql(f"""SELECT p.path_id, p.seq, s.node_id FROM (SELECT *, lag(node_id) OVER (PARTITION BY path_id ORDER BY seq) AS last FROM points_to_fill) p, LATERAL lattice_steps(p.last, p.node_id, {side}) s""")


def detours_by_group(points: DataFrame, sites: DataFrame, dist: DataFrame) -> DataFrame:
    """The matrix kernel by groups, one path a call: the twin of kernel_detours(), which shares equal routes."""
    matrix, chosen = Matrix.of(dist), np.sort(sites.select("site_id").toPandas()["site_id"].to_numpy())
    shared = points.sparkSession.sparkContext.broadcast((matrix, chosen))

    def one(path: pd.DataFrame) -> pd.DataFrame:
        matrix, chosen = shared.value
        best = matrix.detours(np.unique(path["node_id"]), chosen)
        near = best <= FAR // 2
        return pd.DataFrame({"path_id": path["path_id"].iloc[0], "site_id": chosen[near], "metres": best[near].astype(np.int64)})

    return points.select("path_id", "node_id").groupBy("path_id").applyInPandas(one, "path_id long, site_id long, metres long")


def register_sql(spark: SparkSession) -> None:
    """SQL functions over metres and hashes, expanded by the optimizer like built-ins."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION detour_score(metres BIGINT, tau BIGINT) RETURNS BIGINT RETURN CASE WHEN metres <= tau THEN 1000000L ELSE 0L END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION fm_position(h BIGINT) RETURNS INT RETURN CASE WHEN h = 0 THEN 31 ELSE bit_count((h & -h) - 1) END")
