"""Streams run to the end of the given events; each equals its batch query."""

from __future__ import annotations

from pyspark.sql import functions as F

from waysite import fixtures as fx
from waysite.operators import index as ix
from waysite.operators import paths as pt
from waysite.oracles import placement_sql as sql
from waysite.sources.tables import fresh_path, read_table
from waysite.streaming import live

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
EV = "WITH ev AS (SELECT *, CAST(json_extract_string(props, '$.k') AS BIGINT) AS node_id FROM events) "
R2 = 210 * 1.75 * 1.75 / 4


def query(oracle: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if oracle:
            ORACLES[f.__name__] = oracle
        return f

    return add


def stream(spark, sf_dir, files: int = 4):
    folder = fx.once(spark, sf_dir, f"event-folder-{files}", lambda: live.staged(read_table(spark, sf_dir, "events"), files))
    return live.event_stream(spark, folder)


@query(EV + "SELECT node_id, max(n) AS n, opened FROM (SELECT time_bucket(INTERVAL 1 DAY, ts) AS opened, node_id, count(*) AS n FROM ev GROUP BY ALL) t GROUP BY ALL")
def s_tumbling(spark, sf_dir):
    found = live.to_table(live.windowed(stream(spark, sf_dir), "1 day"), "update")
    return found.groupBy("opened", "node_id").agg(F.max("n").alias("n")).withColumn("opened", F.col("opened").cast("timestamp_ntz"))


@query(EV + "SELECT opened, node_id, count(*) AS n FROM (SELECT node_id, unnest([time_bucket(INTERVAL 12 HOUR, ts), time_bucket(INTERVAL 12 HOUR, ts) - INTERVAL 12 HOUR]) AS opened FROM ev) t GROUP BY ALL")
def s_sliding(spark, sf_dir):
    found = live.to_table(live.windowed(stream(spark, sf_dir), "1 day", "12 hours"), "complete")
    last = found.agg(F.max("batch")).scalar()
    return found.where(F.col("batch") == last).select(F.col("opened").cast("timestamp_ntz").alias("opened"), "node_id", "n")


@query(EV + "SELECT opened, node_id, n FROM (SELECT time_bucket(INTERVAL 1 DAY, ts) AS opened, node_id, count(*) AS n FROM ev GROUP BY ALL) t WHERE opened + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 HOUR FROM ev)")
def s_append(spark, sf_dir):
    """Append mode: windows come out once, when the watermark has passed them."""
    found = live.to_table(live.windowed(stream(spark, sf_dir), "1 day"))
    return found.select(F.col("opened").cast("timestamp_ntz").alias("opened"), "node_id", "n")


@query("""WITH o AS (SELECT user_id, ts, coalesce(ts - lag(ts) OVER w >= INTERVAL 6 HOUR, true) AS new, event_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
g AS (SELECT user_id, ts, sum(CAST(new AS INTEGER)) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS k FROM o)
SELECT user_id, min(ts) AS opened, count(*) AS n FROM g GROUP BY user_id, k HAVING max(ts) + INTERVAL 6 HOUR <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events)""")
def s_session(spark, sf_dir):
    found = live.to_table(live.sessions(stream(spark, sf_dir)))
    return found.select("user_id", F.col("opened").cast("timestamp_ntz").alias("opened"), "n")


@query("SELECT CAST(0 AS BIGINT) AS late_rows_counted")
def s_late_dropped(spark, sf_dir):
    """A row of the first hour that arrives after the last file is past the watermark: its window does not reopen."""
    events = read_table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    folder = live.staged(events, 3)
    first = events.agg(F.min("ts").alias("t")).first()["t"]
    late = spark.createDataFrame([(-1, first, -1, "late", 0.0, '{"k": 5}'), (-2, first, -1, "late", 0.0, '{"k": 5}')], live.EVENT_SCHEMA)
    folder2 = fresh_path(spark, "late-files")
    spark.read.parquet(folder).coalesce(1).write.parquet(folder2)
    flow = live.event_stream(spark, folder2).withWatermark("ts", "1 hour")
    state, out = fresh_path(spark, "late-state"), fresh_path(spark, "late-out")

    def run() -> None:
        counted = flow.groupBy(F.window("ts", "1 day").alias("w"), "user_id").agg(F.count("*").alias("n"))
        counted.writeStream.format("parquet").option("path", out).option("checkpointLocation", state).outputMode("append").trigger(availableNow=True).start().awaitTermination()

    run()
    late.coalesce(1).write.mode("append").parquet(folder2)
    run()
    found = spark.read.parquet(out)
    return found.agg(F.count_if(F.col("user_id") == -1).alias("late_rows_counted"))


@query(EV + "SELECT event_id, node_id FROM ev")
def s_dedup(spark, sf_dir):
    events = read_table(spark, sf_dir, "events")
    folder = fx.once(spark, sf_dir, "event-folder-twice", lambda: live.staged(events.unionByName(events), 2))
    return live.to_table(live.deduplicated(live.event_stream(spark, folder), "3650 days"))


@query(sql.chain(sql.lattice(100), sql.DIST, sql.TRIPS, sql.clusters(R2), sql.VISITS) + "SELECT v.event_id, m.cluster_id FROM visits v JOIN member m USING (node_id)")
def s_static_join(spark, sf_dir):
    member = fx.net100(spark, sf_dir).index().member.where("level = 2")
    return live.to_table(live.with_clusters(stream(spark, sf_dir), member))


@query("SELECT v.event_id AS view_id, p.event_id AS purchase_id FROM events v JOIN events p ON p.user_id = v.user_id AND p.event_type = 'purchase' AND p.ts > v.ts AND p.ts <= v.ts + INTERVAL 1 DAY WHERE v.event_type = 'view'")
def s_stream_join(spark, sf_dir):
    return live.to_table(live.bought_after(stream(spark, sf_dir), stream(spark, sf_dir)))


@query(EV + """, s AS (SELECT user_id, ts, event_id, node_id, lag(node_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS last FROM ev)
SELECT user_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1 AS seq, node_id FROM s WHERE last IS NULL OR last <> node_id""")
def s_state_paths(spark, sf_dir):
    return live.to_table(live.user_steps(stream(spark, sf_dir)))


@query(sql.chain(sql.lattice(100), sql.DIST, sql.TRIPS, sql.clusters(R2), sql.DAY_POINTS, sql.detour()) + "SELECT DISTINCT m.cluster_id, p.path_id, d.metres FROM points p JOIN member m USING (node_id) JOIN detour d ON d.path_id = p.path_id AND d.site_id = m.cluster_id")
def s_foreach_updates(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    empty = ix.delete_paths(w.index(), w.points().select("path_id").distinct())
    # Files cut at random, so that micro-batches cut trips and bring their visits out of order.
    events = read_table(spark, sf_dir, "events")
    folder = fx.once(spark, sf_dir, "event-shares", lambda: cut_at_random(events))
    grown = live.update_index(live.event_stream(spark, folder), empty, w.dist(), pt.trips_by_day, pt.day_trip())
    return grown.path.where("level = 2").select("cluster_id", "path_id", "metres")


def cut_at_random(events, files: int = 4) -> str:
    path = fresh_path(events.sparkSession, "event-shares")
    rows = events.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value", "props")
    for k in range(files):
        rows.where(F.pmod(F.xxhash64("event_id"), F.lit(files)) == k).coalesce(1).write.mode("append").parquet(path)
    return path
