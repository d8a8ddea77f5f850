"""Structured streaming over events: windows, late rows, deduplication, joins, stateful paths, and index updates."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, replace

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from waysite.operators import index as ix
from waysite.sources.tables import fresh_path, materialize

EVENT_SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def staged(events: DataFrame, files: int = 4) -> str:
    """The events as a few Parquet files, one after the other in order of time: the folder that the stream reads."""
    path = fresh_path(events.sparkSession, "event-files")
    rows = events.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value", "props")
    micros = F.unix_micros("ts")
    cuts = rows.agg(F.percentile_approx(micros, [k / files for k in range(1, files)]).alias("c")).first()["c"] or []
    edges = [None, *cuts, None]
    for low, high in zip(edges, edges[1:], strict=False):
        part = rows.where((F.lit(True) if low is None else micros > low) & (F.lit(True) if high is None else micros <= high))
        part.coalesce(1).sortWithinPartitions("ts", "event_id").write.mode("append").parquet(path)
    return path


def event_stream(spark: SparkSession, folder: str, files_per_trigger: int = 1) -> DataFrame:
    raw = spark.readStream.schema(EVENT_SCHEMA).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)
    return raw.withColumn("node_id", F.get_json_object("props", "$.k").cast("long"))


def to_table(stream: DataFrame, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Run a stream to the end of its input. Append goes to a Parquet folder in the shared place; update and complete
    keep, batch by batch, what foreachBatch was given last for a key."""
    spark = stream.sparkSession
    at = checkpoint or fresh_path(spark, "stream-state")
    if mode == "append":
        out = fresh_path(spark, "stream-out")
        writer = stream.writeStream.format("parquet").option("path", out)
        schema = stream.schema
        writer.option("checkpointLocation", at).outputMode("append").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(schema).parquet(out)
    base = fresh_path(spark, "stream-out")

    def keep(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{base}/b={number}")

    stream.writeStream.foreachBatch(keep).option("checkpointLocation", at).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(base).drop("b")


def windowed(stream: DataFrame, width: str, slide: str | None = None, lateness: str = "1 hour") -> DataFrame:
    """Visits of each node by tumbling or sliding windows; rows later than the lateness are dropped."""
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    counted = stream.withWatermark("ts", lateness).groupBy(window.alias("w"), "node_id").agg(F.count("*").alias("n"))
    return counted.select(F.col("w.start").alias("opened"), "node_id", "n")


def sessions(stream: DataFrame, gap: str = "6 hours", lateness: str = "1 hour") -> DataFrame:
    grouped = stream.withWatermark("ts", lateness).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return grouped.select(F.col("w.start").alias("opened"), "user_id", "n")


def deduplicated(stream: DataFrame, lateness: str = "1 day") -> DataFrame:
    return stream.withWatermark("ts", lateness).dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "node_id")


def with_clusters(stream: DataFrame, member: DataFrame) -> DataFrame:
    """Each event with the cluster of its node: a static side."""
    return stream.join(member.select("node_id", "cluster_id"), "node_id").select("event_id", "cluster_id")


def bought_after(views: DataFrame, purchases: DataFrame, within: str = "1 day") -> DataFrame:
    """Views followed by a purchase of the same user: two streams, each with its watermark, so state stays bounded."""
    v = views.where("event_type = 'view'").select(F.col("event_id").alias("view_id"), F.col("user_id").alias("v_user"), F.col("ts").alias("v_ts")).withWatermark("v_ts", "1 hour")
    p = purchases.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", "ts").withWatermark("ts", "1 hour")
    near = (F.col("v_user") == F.col("user_id")) & (F.col("ts") > F.col("v_ts")) & (F.col("ts") <= F.col("v_ts") + F.expr(f"INTERVAL {within}"))
    return v.join(p, near).select("view_id", "purchase_id")


def user_steps(stream: DataFrame) -> DataFrame:
    """Stateful: a user's node changes, in order of arrival: a visit to the node the user is at already gives no step."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        last, count = state.get if state.exists else (-1, 0)
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        out = []
        for node in rows["node_id"]:
            if node != last:
                out.append((key[0], count, int(node)))
                last, count = int(node), count + 1
        state.update((last, count))
        yield pd.DataFrame(out, columns=["user_id", "seq", "node_id"])

    return stream.select("user_id", "ts", "event_id", "node_id").groupBy("user_id").applyInPandasWithState(step, "user_id long, seq long, node_id long", "last long, count long", "append", GroupStateTimeout.NoTimeout)


@dataclass(frozen=True)
class IndexStore:
    """What a stream of index updates keeps in the shared folder, one part a micro-batch: rows, the raw visits with their
    path's number; paths, the index rows of the paths that the batch touched. A part that is written again after a
    failure replaces itself, so a restart neither loses nor doubles anything."""

    spark: SparkSession
    folder: str

    def _parts(self, name: str, upto: int) -> list[str]:
        path = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.folder}/{name}")
        fs = path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())
        found = [f.getPath().getName() for f in fs.listStatus(path)] if fs.exists(path) else []
        whole = [x for x in found if fs.exists(self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.folder}/{name}/{x}/_SUCCESS"))]
        return [f"{self.folder}/{name}/{x}" for x in sorted(whole) if int(x.removeprefix("part=")) <= upto]

    def write(self, df: DataFrame, name: str, part: int) -> None:
        df.write.mode("overwrite").parquet(f"{self.folder}/{name}/part={part}")

    def read(self, name: str, upto: int = 1 << 62) -> DataFrame | None:
        parts = self._parts(name, upto)
        return self.spark.read.option("basePath", f"{self.folder}/{name}").parquet(*parts) if parts else None

    def index_rows(self) -> DataFrame:
        """(level, cluster_id, path_id, metres): of each path the rows of the last part that touched it."""
        rows = self.read("rows").groupBy("path_id").agg(F.max("part").alias("last"))
        return self.read("paths").join(rows, "path_id").where(F.col("part") == F.col("last")).select("level", "cluster_id", "path_id", "metres")

    def newest(self) -> DataFrame:
        """(path_id, seen): the last visit of each path."""
        return self.read("rows").groupBy("path_id").agg(F.max("ts").alias("seen"))


def update_index(stream: DataFrame, index: ix.Index, dist: DataFrame, path_of: Callable[[DataFrame], DataFrame], key: Column, checkpoint: str | None = None, horizon_days: int | None = None, history: DataFrame | None = None) -> ix.Index:
    """Every micro-batch of visits is taken up by the index. The paths that a batch touches are made anew from all their
    visits so far, so a trip may be cut anywhere and its visits may come late or in any order. path_of: visits -> points;
    key: the path_id of a visit; history: the visits behind the paths that the index has already (without them such a
    path is replaced by what the stream brings of it). Paths whose last visit is horizon_days or more before the newest
    one leave the index. All state is beside the stream's checkpoint: a restart goes on where the last one ended."""
    spark = stream.sparkSession
    at = checkpoint or fresh_path(spark, "index-stream")
    store = IndexStore(spark, f"{at}/index-store")
    if store.read("paths", -1) is None:
        base = index.path.select("level", "cluster_id", "path_id", "metres")
        unseen = base.select("path_id").distinct().select(*(F.lit(None).cast(f.dataType).alias(f.name) for f in stream.schema), "path_id")
        known = unseen if history is None else history.select(*stream.columns).withColumn("path_id", key)
        store.write(known, "rows", -1)
        store.write(base, "paths", -1)

    def apply(batch: DataFrame, number: int) -> None:
        store.write(batch.withColumn("path_id", key), "rows", number)
        rows = store.read("rows", number)
        touched = rows.where(F.col("part") == number).select("path_id").distinct()
        visits = rows.join(touched, "path_id", "left_semi").where(F.col("ts").isNotNull()).select(*batch.columns)
        store.write(ix.cluster_paths(path_of(visits), index.member, dist), "paths", number)

    stream.writeStream.foreachBatch(apply).option("checkpointLocation", f"{at}/stream").trigger(availableNow=True).start().awaitTermination()
    path = store.index_rows()
    if horizon_days is not None:
        seen = store.newest()
        newest = seen.agg(F.max("seen")).first()[0]
        if newest is not None:
            path = path.join(seen.where(F.col("seen") > F.lit(newest) - F.expr(f"INTERVAL {horizon_days} DAYS")), "path_id", "left_semi")
    return replace(index, path=materialize(path, "index-path"))
