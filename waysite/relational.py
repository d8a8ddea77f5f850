"""Relational operators around the methods, over the given tables, each with its SQL twin."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from waysite import fixtures as fx
from waysite.api import Workspace
from waysite.functions import preference as pref
from waysite.functions import udfs
from waysite.operators import paths as pt
from waysite.oracles import placed_sql as ps
from waysite.oracles import placement_sql as sql
from waysite.sources import tables as tb
from waysite.sources.tables import read_table

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
K = "CAST(json_extract_string(props, '$.k') AS BIGINT)"


def query(oracle: str | None = None, name: str | None = None):
    def add(f):
        QUERIES[name or f.__name__] = f
        if oracle:
            ORACLES[name or f.__name__] = oracle
        return f

    return add


def node():
    return F.get_json_object("props", "$.k").cast("long")


def events(spark: SparkSession, sf_dir: str, *more: str) -> DataFrame:
    return read_table(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type", "value", "props").withColumn("node_id", node())


EV = f"WITH ev AS (SELECT *, {K} AS node_id FROM events) "


@query(EV + "SELECT event_id, CAST(node_id AS INTEGER) AS node_id, CAST(value AS DECIMAL(12,2)) AS amount, year(ts) AS y FROM ev")
def q_project_cast(spark, sf_dir):
    return events(spark, sf_dir).select("event_id", F.col("node_id").cast("int").alias("node_id"), F.col("value").cast("decimal(12,2)").alias("amount"), F.year("ts").cast("long").alias("y"))


@query("SELECT o_orderkey, coalesce(o_orderpriority, 'none') AS priority FROM orders WHERE o_totalprice BETWEEN 1000 AND 100000 AND o_orderstatus IN ('F', 'O') AND o_custkey IS NOT DISTINCT FROM o_custkey AND regexp_matches(o_orderpriority, '^[1-3]')")
def q_filter_null_safe(spark, sf_dir):
    o = read_table(spark, sf_dir, "orders")
    return o.where(F.col("o_totalprice").between(1000, 100000) & F.col("o_orderstatus").isin("F", "O") & F.col("o_custkey").eqNullSafe(F.col("o_custkey")) & F.col("o_orderpriority").rlike("^[1-3]")).select("o_orderkey", F.coalesce("o_orderpriority", F.lit("none")).alias("priority"))


JOINED = "SELECT s_nationkey, count(*) AS n, CAST(sum(l_linenumber) AS BIGINT) AS lines FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY s_nationkey"


def _hinted(hint: str):
    def run(spark, sf_dir):
        s = read_table(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey")
        lines = read_table(spark, sf_dir, "lineitem", "l_suppkey", "l_linenumber")
        return lines.join(s.hint(hint), F.col("l_suppkey") == F.col("s_suppkey")).groupBy("s_nationkey").agg(F.count("*").alias("n"), F.sum("l_linenumber").alias("lines"))

    return run


for _name, _hint in (("q_join_broadcast", "broadcast"), ("q_join_merge", "merge"), ("q_join_shuffle_hash", "shuffle_hash")):
    query(JOINED, _name)(_hinted(_hint))


@query("SELECT n_nationkey, n_name, count(s_suppkey) AS n FROM nation LEFT JOIN supplier ON n_nationkey = s_nationkey GROUP BY ALL")
def q_join_left(spark, sf_dir):
    n, s = read_table(spark, sf_dir, "nation"), read_table(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey")
    return n.join(s, F.col("n_nationkey") == F.col("s_nationkey"), "left").groupBy("n_nationkey", "n_name").agg(F.count("s_suppkey").alias("n"))


@query("SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a FULL JOIN (SELECT n_nationkey FROM nation WHERE n_regionkey = 1) b ON a.n_nationkey = b.n_nationkey + 3")
def q_join_full(spark, sf_dir):
    a = read_table(spark, sf_dir, "nation", "n_nationkey").withColumnRenamed("n_nationkey", "a")
    b = read_table(spark, sf_dir, "nation", "n_nationkey", "n_regionkey").where("n_regionkey = 1").select(F.col("n_nationkey").alias("b"))
    return a.join(b, F.col("a") == F.col("b") + 3, "full")


@query("SELECT a.n_nationkey AS a, b.n_nationkey AS b, c.n_nationkey AS c FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey JOIN nation c ON b.n_nationkey < c.n_nationkey")
def q_join_theta_triples(spark, sf_dir):
    n = read_table(spark, sf_dir, "nation", "n_nationkey")
    a, b, c = (n.withColumnRenamed("n_nationkey", x) for x in "abc")
    return a.join(b, F.col("a") < F.col("b")).join(c, F.col("b") < F.col("c"))


@query("WITH p AS (SELECT s_suppkey AS id, s_suppkey * 37 % 1000 AS x, s_suppkey * 91 % 1000 AS y FROM supplier) SELECT a.id AS a, b.id AS b FROM p a JOIN p b ON a.id < b.id AND (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) <= 10000")
def q_join_range_cells(spark, sf_dir):
    p = read_table(spark, sf_dir, "supplier", "s_suppkey").select(F.col("s_suppkey").alias("id"), F.pmod(F.col("s_suppkey") * 37, F.lit(1000)).alias("x"), F.pmod(F.col("s_suppkey") * 91, F.lit(1000)).alias("y"))
    grid = F.array(*(F.lit(d) for d in (-1, 0, 1)))
    near = p.withColumn("dx", F.explode(grid)).withColumn("dy", F.explode(grid)).select(F.col("id").alias("b"), F.col("x").alias("bx"), F.col("y").alias("by"), (F.floor(F.col("x") / 100) + F.col("dx")).alias("cx"), (F.floor(F.col("y") / 100) + F.col("dy")).alias("cy"))
    own = p.select(F.col("id").alias("a"), "x", "y", F.floor(F.col("x") / 100).alias("cx"), F.floor(F.col("y") / 100).alias("cy"))
    square = (F.col("x") - F.col("bx")) * (F.col("x") - F.col("bx")) + (F.col("y") - F.col("by")) * (F.col("y") - F.col("by"))
    return own.join(near, ["cx", "cy"]).where((F.col("a") < F.col("b")) & (square <= 10000)).select("a", "b")


@query("SELECT v.event_id AS view_id, count(p.event_id) AS purchases FROM events v LEFT JOIN events p ON p.user_id = v.user_id AND p.event_type = 'purchase' AND p.ts > v.ts AND p.ts <= v.ts + INTERVAL 1 DAY WHERE v.event_type = 'view' GROUP BY v.event_id")
def q_join_interval(spark, sf_dir):
    e = events(spark, sf_dir)
    v = e.where("event_type = 'view'").select("event_id", "user_id", "ts")
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("p_id"), F.col("user_id").alias("p_user"), F.col("ts").alias("p_ts"))
    within = (F.col("user_id") == F.col("p_user")) & (F.col("p_ts") > F.col("ts")) & (F.col("p_ts") <= F.col("ts") + F.expr("INTERVAL 1 DAY"))
    return v.join(p, within, "left").groupBy(F.col("event_id").alias("view_id")).agg(F.count("p_id").alias("purchases"))


@query("WITH o AS (SELECT o_custkey, o_orderdate, max(o_orderkey) AS o_orderkey FROM orders GROUP BY ALL), e AS (SELECT user_id, ts, event_id FROM events) SELECT e.event_id, o.o_orderkey FROM e ASOF LEFT JOIN o ON o.o_custkey = e.user_id AND o.o_orderdate <= e.ts")
def q_join_asof(spark, sf_dir):
    e = events(spark, sf_dir).select(F.col("user_id").alias("k"), F.col("ts").alias("t"), "event_id", F.lit(None).cast("long").alias("o_orderkey"), F.lit(1).alias("last"))
    o = read_table(spark, sf_dir, "orders", "o_custkey", "o_orderdate", "o_orderkey").groupBy("o_custkey", "o_orderdate").agg(F.max("o_orderkey").alias("o_orderkey")).select(F.col("o_custkey").alias("k"), F.col("o_orderdate").alias("t"), F.lit(None).cast("long").alias("event_id"), "o_orderkey", F.lit(0).alias("last"))
    w = Window.partitionBy("k").orderBy("t", "last").rowsBetween(Window.unboundedPreceding, 0)
    return e.unionByName(o).withColumn("o_orderkey", F.last("o_orderkey", ignorenulls=True).over(w)).where("event_id IS NOT NULL").select("event_id", "o_orderkey")


@query(sql.chain(sql.DAY_POINTS) + "SELECT DISTINCT path_id FROM points p WHERE EXISTS (SELECT 1 FROM points q WHERE q.path_id = p.path_id AND q.node_id = 55)")
def q_semi_touching_site(spark, sf_dir):
    p = fx.net100(spark, sf_dir).points()
    return p.select("path_id").distinct().join(p.where("node_id = 55").select("path_id"), "path_id", "left_semi")


@query(sql.chain(*sql.day_cover(240)) + "SELECT DISTINCT path_id FROM points WHERE path_id NOT IN (SELECT path_id FROM cover WHERE site_id IN (55, 33))")
def q_anti_uncovered(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return w.points().select("path_id").distinct().join(w.cover(pref.binary(240)).where(F.col("site_id").isin(55, 33)).select("path_id"), "path_id", "left_anti")


@query("SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a CROSS JOIN nation b")
def q_cross_grid(spark, sf_dir):
    n = read_table(spark, sf_dir, "nation", "n_nationkey")
    return n.withColumnRenamed("n_nationkey", "a").crossJoin(n.withColumnRenamed("n_nationkey", "b"))  # 25 x 25 by definition


@query("SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 3", "q_lateral_topk")
@query("SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 3")
def q_topk_per_group(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy(F.col("o_totalprice").desc(), "o_orderkey")
    return read_table(spark, sf_dir, "orders", "o_custkey", "o_orderkey", "o_totalprice").withColumn("r", F.row_number().over(w)).where("r <= 3").select("o_custkey", "o_orderkey")


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
def q_topk_global(spark, sf_dir):
    return read_table(spark, sf_dir, "orders", "o_orderkey", "o_totalprice").orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(25)


@query(EV + "SELECT node_id, count(*) AS n, round(avg(value), 6) AS mean, max(ts) AS latest FROM ev GROUP BY node_id")
def q_agg_hash(spark, sf_dir):
    return events(spark, sf_dir).groupBy("node_id").agg(F.count("*").alias("n"), F.round(F.avg("value"), 6).alias("mean"), F.max("ts").alias("latest"))


@query(EV + "SELECT user_id, string_agg(CAST(node_id AS VARCHAR), '>' ORDER BY ts, event_id) AS route FROM ev GROUP BY user_id")
def q_agg_sorted_arrays(spark, sf_dir):
    gathered = events(spark, sf_dir).groupBy("user_id").agg(F.sort_array(F.collect_list(F.struct("ts", "event_id", "node_id"))).alias("v"))
    return gathered.select("user_id", F.array_join(F.transform("v", lambda x: x["node_id"].cast("string")), ">").alias("route"))


@query(EV + "SELECT node_id, count(DISTINCT user_id) AS users, count(DISTINCT CAST(ts AS DATE)) AS days FROM ev GROUP BY node_id")
def q_agg_distinct(spark, sf_dir):
    return events(spark, sf_dir).groupBy("node_id").agg(F.countDistinct("user_id").alias("users"), F.countDistinct(F.to_date("ts")).alias("days"))


@query()
def q_agg_approx_distinct(spark, sf_dir):
    return events(spark, sf_dir).groupBy("node_id").agg(F.approx_count_distinct("user_id").alias("users"))


@query(EV + "SELECT node_id, bit_or(CAST(1 AS BIGINT) << (user_id % 31)) AS word FROM ev GROUP BY node_id")
def q_agg_bit_or(spark, sf_dir):
    return events(spark, sf_dir).groupBy("node_id").agg(F.bit_or(F.expr("shiftleft(1L, cast(user_id % 31 as int))")).alias("word"))


@query(EV + "SELECT node_id, arg_min(event_id, struct_pack(ts, event_id)) AS first, arg_max(event_id, struct_pack(ts, event_id)) AS latest FROM ev GROUP BY node_id")
def q_agg_min_by(spark, sf_dir):
    return events(spark, sf_dir).groupBy("node_id").agg(F.min_by("event_id", F.struct("ts", "event_id")).alias("first"), F.max_by("event_id", F.struct("ts", "event_id")).alias("latest"))


@query("SELECT l_returnflag, round(quantile_cont(l_quantity, 0.5), 6) AS median, round(quantile_cont(l_quantity, 0.9), 6) AS p90 FROM lineitem GROUP BY l_returnflag")
def q_agg_percentile(spark, sf_dir):
    return read_table(spark, sf_dir, "lineitem", "l_returnflag", "l_quantity").groupBy("l_returnflag").agg(F.round(F.percentile("l_quantity", 0.5), 6).alias("median"), F.round(F.percentile("l_quantity", 0.9), 6).alias("p90"))


@query(EV + "SELECT user_id, count(*) FILTER (WHERE event_type = 'view') AS views, count(*) FILTER (WHERE event_type = 'purchase') AS purchases FROM ev GROUP BY user_id")
def q_agg_filter(spark, sf_dir):
    return events(spark, sf_dir).groupBy("user_id").agg(F.count_if(F.col("event_type") == "view").alias("views"), F.count_if(F.col("event_type") == "purchase").alias("purchases"))


BLOCKS = EV + "SELECT node_id // 25 AS block, event_type, CAST(grouping_id(node_id // 25, event_type) AS BIGINT) AS gid, count(*) AS n FROM ev GROUP BY "


@query(BLOCKS + "GROUPING SETS ((node_id // 25, event_type), (event_type), ())")
def q_grouping_sets(spark, sf_dir):
    e = events(spark, sf_dir).withColumn("block", F.floor(F.col("node_id") / 25))
    return e.groupingSets([[F.col("block"), F.col("event_type")], [F.col("event_type")], []], "block", "event_type").agg(F.grouping_id("block", "event_type").alias("gid"), F.count("*").alias("n"))


@query(BLOCKS + "CUBE (node_id // 25, event_type)")
def q_cube(spark, sf_dir):
    return events(spark, sf_dir).withColumn("block", F.floor(F.col("node_id") / 25)).cube("block", "event_type").agg(F.grouping_id().alias("gid"), F.count("*").alias("n"))


@query(BLOCKS + "ROLLUP (node_id // 25, event_type)")
def q_rollup(spark, sf_dir):
    return events(spark, sf_dir).withColumn("block", F.floor(F.col("node_id") / 25)).rollup("block", "event_type").agg(F.grouping_id().alias("gid"), F.count("*").alias("n"))


@query(EV + "SELECT node_id, count(*) FILTER (WHERE event_type = 'view') AS view, count(*) FILTER (WHERE event_type = 'purchase') AS purchase FROM ev GROUP BY node_id")
def q_pivot(spark, sf_dir):
    return events(spark, sf_dir).groupBy("node_id").pivot("event_type", ["view", "purchase"]).count().fillna(0)


@query(EV + "SELECT node_id, kind, n FROM (SELECT node_id, 'rows' AS kind, count(*) AS n FROM ev GROUP BY node_id UNION ALL SELECT node_id, 'users', count(DISTINCT user_id) FROM ev GROUP BY node_id) u")
def q_unpivot(spark, sf_dir):
    wide = events(spark, sf_dir).groupBy("node_id").agg(F.count("*").alias("rows"), F.countDistinct("user_id").alias("users"))
    return wide.unpivot("node_id", ["rows", "users"], "kind", "n")


@query("""WITH c AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey) SELECT o_custkey, CAST(row_number() OVER (ORDER BY n DESC, o_custkey) AS INTEGER) AS rn, CAST(rank() OVER (ORDER BY n DESC) AS INTEGER) AS rk, CAST(dense_rank() OVER (ORDER BY n DESC) AS INTEGER) AS dr,
CAST(ntile(4) OVER (ORDER BY n DESC, o_custkey) AS INTEGER) AS q, round(percent_rank() OVER (ORDER BY n DESC), 9) AS pr, round(cume_dist() OVER (ORDER BY n DESC), 9) AS cd FROM c""")
def q_win_rank(spark, sf_dir):
    c = read_table(spark, sf_dir, "orders", "o_custkey").groupBy("o_custkey").agg(F.count("*").alias("n"))
    strict, loose = Window.orderBy(F.col("n").desc(), "o_custkey"), Window.orderBy(F.col("n").desc())
    return c.select("o_custkey", F.row_number().over(strict).alias("rn"), F.rank().over(loose).alias("rk"), F.dense_rank().over(loose).alias("dr"), F.ntile(4).over(strict).alias("q"), F.round(F.percent_rank().over(loose), 9).alias("pr"), F.round(F.cume_dist().over(loose), 9).alias("cd"))


@query(EV + "SELECT event_id, lag(node_id) OVER w AS before, lead(node_id) OVER w AS after FROM ev WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def q_win_lag_lead(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return events(spark, sf_dir).select("event_id", F.lag("node_id").over(w).alias("before"), F.lead("node_id").over(w).alias("after"))


@query(EV + "SELECT event_id, first_value(node_id) OVER w AS opening, last_value(node_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS closing FROM ev WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def q_win_first_last(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return events(spark, sf_dir).select("event_id", F.first("node_id").over(w).alias("opening"), F.last("node_id").over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("closing"))


@query(EV + "SELECT event_id, count(*) OVER (PARTITION BY node_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS visits FROM ev")
def q_win_rows_frame(spark, sf_dir):
    w = Window.partitionBy("node_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return events(spark, sf_dir).select("event_id", F.count("*").over(w).alias("visits"))


@query(EV + "SELECT event_id, count(*) OVER (PARTITION BY node_id ORDER BY CAST(floor(epoch(ts)) AS BIGINT) RANGE BETWEEN 21600 PRECEDING AND CURRENT ROW) AS recent FROM ev")
def q_win_range_frame(spark, sf_dir):
    w = Window.partitionBy("node_id").orderBy(F.unix_timestamp("ts")).rangeBetween(-21600, 0)
    return events(spark, sf_dir).select("event_id", F.count("*").over(w).alias("recent"))


COVERS = sql.chain(*sql.day_cover(240), "b AS (SELECT path_id, site_id FROM cover WHERE metres <= 120)", "a AS (SELECT path_id, site_id FROM cover WHERE site_id < 50)")


def _two_covers(spark, sf_dir):
    c = fx.net100(spark, sf_dir).cover(pref.binary(240))
    return c.where("site_id < 50").select("path_id", "site_id"), c.where("metres <= 120").select("path_id", "site_id")


for _name, _sql, _method in (("q_union", "UNION", lambda a, b: a.union(b).distinct()), ("q_union_all", "UNION ALL", lambda a, b: a.unionAll(b)), ("q_union_by_name", "UNION ALL", lambda a, b: a.unionByName(b.select("site_id", "path_id"))), ("q_intersect", "INTERSECT", lambda a, b: a.intersect(b)), ("q_intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)), ("q_except", "EXCEPT", lambda a, b: a.subtract(b)), ("q_except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b))):
    query(COVERS + f"SELECT * FROM a {_sql} SELECT * FROM b", _name)(lambda spark, sf_dir, m=_method: m(*_two_covers(spark, sf_dir)))


@query("SELECT event_id FROM events WHERE (CAST(48271 AS BIGINT) * event_id + 11) % 2147483647 < 214748364")
def q_sample_hash(spark, sf_dir):
    return events(spark, sf_dir).where(F.pmod(F.lit(48271).cast("long") * F.col("event_id") + 11, F.lit(2147483647)) < 214748364).select("event_id")


@query()
def q_sample_stratified(spark, sf_dir):
    return events(spark, sf_dir).sampleBy("event_type", {"view": 0.1, "purchase": 0.5}, seed=7).select("event_id", "event_type")


@query("SELECT DISTINCT l_suppkey, l_returnflag FROM lineitem")
def q_distinct(spark, sf_dir):
    return read_table(spark, sf_dir, "lineitem", "l_suppkey", "l_returnflag").distinct()


@query("SELECT l_orderkey, l_linenumber, count(*) AS n FROM lineitem GROUP BY ALL HAVING count(*) > 1")
def q_duplicate_keys(spark, sf_dir):
    return read_table(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber").groupBy("l_orderkey", "l_linenumber").agg(F.count("*").alias("n")).where("n > 1")


@query("SELECT count(*) AS n FROM (SELECT DISTINCT l_orderkey, l_linenumber FROM lineitem)")
def q_dedup_by_key(spark, sf_dir):
    return read_table(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_suppkey").dropDuplicates(["l_orderkey", "l_linenumber"]).agg(F.count("*").alias("n"))


@query(sql.chain(sql.lattice_over(sql.HOMES), "hops(node_id, h) AS (SELECT CAST(0 AS BIGINT), 0 UNION SELECT e.dst, h + 1 FROM hops JOIN edges e ON e.src = hops.node_id WHERE h < 3)") + "SELECT node_id, CAST(min(h) AS INTEGER) AS hops FROM hops GROUP BY node_id")
def q_cte_recursive(spark, sf_dir):
    fx.net25(spark, sf_dir).given_net(lambda: fx.home_nodes(spark, sf_dir)).edges.createOrReplaceTempView("net25_roads")
    return spark.sql("WITH RECURSIVE hops(node_id, h) AS (SELECT 0L, 0 UNION ALL SELECT e.dst, h + 1 FROM hops JOIN net25_roads e ON e.src = hops.node_id WHERE h < 3) SELECT node_id, min(h) AS hops FROM hops GROUP BY node_id")


@query("SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM orders)")
def q_subquery_scalar(spark, sf_dir):
    o = read_table(spark, sf_dir, "orders", "o_orderkey", "o_totalprice")
    return o.where(F.col("o_totalprice") > o.agg(F.avg("o_totalprice") * 1.5).scalar()).select("o_orderkey")


@query("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')")
def q_subquery_exists(spark, sf_dir):
    c, o = read_table(spark, sf_dir, "customer", "c_custkey"), read_table(spark, sf_dir, "orders", "o_custkey", "o_orderstatus")
    return c.where(o.where((F.col("o_custkey") == F.col("c_custkey").outer()) & (F.col("o_orderstatus") == "F")).exists())


@query("SELECT n_nationkey, unnest(range(0, n_nationkey % 3 + 1)) AS step FROM nation")
def q_sequence_explode(spark, sf_dir):
    return read_table(spark, sf_dir, "nation", "n_nationkey").select("n_nationkey", F.explode(F.sequence(F.lit(0).cast("long"), F.pmod(F.col("n_nationkey").cast("long"), F.lit(3)))).alias("step"))


@query(sql.chain(sql.DAY_POINTS) + "SELECT path_id, seq, node_id FROM points")
def q_posexplode(spark, sf_dir):
    arrays = pt.path_arrays(fx.net100(spark, sf_dir).points())
    return arrays.select("path_id", F.posexplode("nodes").alias("seq", "node_id"))


@query(sql.chain(sql.DAY_POINTS) + "SELECT path_id, min(seq) AS seq FROM points GROUP BY path_id")
def q_inline(spark, sf_dir):
    p = fx.net100(spark, sf_dir).points().groupBy("path_id").agg(F.array(F.struct(F.min("seq").alias("seq"))).alias("r"))
    return p.select("path_id", F.inline("r"))


EVENT_ROWS = "SELECT event_id, user_id, event_type, props FROM events"
for _fmt in ("csv", "json", "orc", "parquet"):
    query(EVENT_ROWS, f"q_source_{_fmt}")(lambda spark, sf_dir, f=_fmt: tb.round_trip(events(spark, sf_dir).select("event_id", "user_id", "event_type", "props"), f, **({"header": "true", "escape": '"'} if f == "csv" else {})))


@query("SELECT count(*) AS n FROM events")
def q_source_text(spark, sf_dir):
    return tb.round_trip(events(spark, sf_dir).select(F.col("props").alias("value")), "text").agg(F.count("*").alias("n"))


@query("SELECT event_type, count(*) AS n FROM events WHERE event_type = 'view' GROUP BY event_type")
def q_sink_partitioned(spark, sf_dir):
    path = tb.fresh_path(spark, "by-type")
    tb.write_partitioned(events(spark, sf_dir).select("event_id", "event_type"), path, "event_type")
    return spark.read.parquet(path).where("event_type = 'view'").groupBy("event_type").agg(F.count("*").alias("n"))


@query("SELECT user_id, count(*) AS n FROM events GROUP BY user_id")
def q_sink_bucketed(spark, sf_dir):
    table = tb.write_bucketed(events(spark, sf_dir).select("event_id", "user_id"), "waysite_events_by_user", 8, "user_id")
    return table.groupBy("user_id").agg(F.count("*").alias("n"))


# -- scalar functions


@query("SELECT s_suppkey, round(sqrt(s_suppkey), 9) AS root, CAST(ceil(s_acctbal) AS BIGINT) AS up, CAST(floor(s_acctbal) AS BIGINT) AS down, CAST((s_suppkey * 7) % 11 AS BIGINT) AS m, s_suppkey << 3 AS shifted, CAST(bit_count(s_suppkey) AS INTEGER) AS ones FROM supplier")
def f_math(spark, sf_dir):
    k = F.col("s_suppkey")
    return read_table(spark, sf_dir, "supplier", "s_suppkey", "s_acctbal").select("s_suppkey", F.round(F.sqrt(k), 9).alias("root"), F.ceil("s_acctbal").alias("up"), F.floor("s_acctbal").alias("down"), F.pmod(k * 7, F.lit(11)).alias("m"), F.shiftleft(k, 3).alias("shifted"), F.bit_count(k).alias("ones"))


@query("SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, lower(substr(url, 1, 12)) AS head, len(string_split(url, '/')) AS parts FROM pages")
def f_string(spark, sf_dir):
    return read_table(spark, sf_dir, "pages", "page_id", "url").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host"), F.lower(F.substring("url", 1, 12)).alias("head"), F.size(F.split("url", "/")).cast("long").alias("parts"))


@query("SELECT event_id, date_trunc('hour', ts) AS hour, date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS day, epoch_us(ts) AS micros FROM events")
def f_date(spark, sf_dir):
    return events(spark, sf_dir).select("event_id", F.date_trunc("hour", "ts").alias("hour"), F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")).cast("long").alias("day"), F.unix_micros(F.col("ts").cast("timestamp")).alias("micros"))


@query("SELECT label, round(avg(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x))), 4) AS norm, max(len(embedding)) AS dims FROM embeddings GROUP BY label")
def f_array(spark, sf_dir):
    e = read_table(spark, sf_dir, "embeddings", "label", "embedding").withColumn("q", F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x), F.lit(0.0), lambda a, b: a + b))
    return e.groupBy("label").agg(F.round(F.avg("q"), 4).alias("norm"), F.max(F.size("embedding")).cast("long").alias("dims"))


@query("SELECT n_nationkey, n_regionkey AS region_of FROM nation WHERE n_nationkey < 10")
def f_map(spark, sf_dir):
    one = read_table(spark, sf_dir, "nation", "n_nationkey", "n_regionkey").where("n_nationkey < 10").groupBy().agg(F.map_from_arrays(F.collect_list("n_nationkey"), F.collect_list("n_regionkey")).alias("m"))
    return one.select(F.explode(F.map_entries("m")).alias("e")).select(F.col("e.key").alias("n_nationkey"), F.col("e.value").alias("region_of"))


@query(EV + "SELECT event_id, node_id AS k, '{\"node\":' || node_id || '}' AS packed FROM ev")
def f_json(spark, sf_dir):
    e = events(spark, sf_dir).withColumn("parsed", F.from_json("props", "k long"))
    return e.select("event_id", F.col("parsed.k").alias("k"), F.to_json(F.struct(F.col("parsed.k").alias("node"))).alias("packed"))


@query("WITH r AS (SELECT conv_id, turn, role, lag(role) OVER (PARTITION BY conv_id ORDER BY turn) AS last FROM conversations) SELECT conv_id, string_agg(role, '>' ORDER BY turn) AS runs FROM r WHERE last IS NULL OR last <> role GROUP BY conv_id")
def f_run_collapse(spark, sf_dir):
    w = Window.partitionBy("conv_id").orderBy("turn")
    r = read_table(spark, sf_dir, "conversations", "conv_id", "turn", "role").withColumn("last", F.lag("role").over(w)).where(F.col("last").isNull() | (F.col("last") != F.col("role")))
    return r.groupBy("conv_id").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("turn", "role"))), lambda x: x["role"]), ">").alias("runs"))


# -- user-defined functions and SQL surface, each against its built-in twin

LINEAR = sql.chain(*sql.day_cover(400, "linear")) + "SELECT path_id, site_id, score FROM cover"


@query(LINEAR)
def u_preference_pandas(spark, sf_dir):
    d = fx.net100(spark, sf_dir).detours().where("metres <= 400")
    return d.select("path_id", "site_id", udfs.scored(lambda m: 1 - m / 400.0)(F.col("metres")).alias("score")).where("score > 0")


@query(sql.chain(*sql.day_cover(), sql.fm_words(4)) + "SELECT site_id, copy, word FROM words")
def u_word_or_pandas(spark, sf_dir):
    return udfs.fm_words_by_udf(spark, fx.net100(spark, sf_dir).cover(pref.binary(400)), 4)


@query(sql.chain(sql.DAY_POINTS, sql.filled(10)) + "SELECT path_id, count(*) AS n FROM filled_points GROUP BY path_id")
def u_fill_gaps_udtf(spark, sf_dir):
    return udfs.fill_by_udtf(spark, fx.net100(spark, sf_dir).points(), 10).groupBy("path_id").agg(F.count("*").alias("n"))


@query(sql.chain(sql.lattice(100), sql.DIST, sql.DAY_POINTS, sql.detour()) + "SELECT path_id, site_id, metres FROM detour")
def u_detours_grouped(spark, sf_dir):
    w = fx.net100(spark, sf_dir)
    return udfs.detours_by_group(w.points(), w.sites(), w.dist())


def workspace(spark, sf_dir) -> Workspace:
    w = fx.net100(spark, sf_dir)
    return Workspace(spark, w.points(), w.sites(), w.net().edges, w.detours(), w.index())


@query(sql.chain(*sql.day_cover(preference="linear")) + "SELECT path_id, site_id, metres, score FROM cover")
def api_cover_of(spark, sf_dir):
    return workspace(spark, sf_dir).cover_of(pref.linear(400))


@query(ps.statement(ps.DAYS, *ps.serving(800), ps.cover("cov", 800, source=f"est{ps.level_of(800)}"), ps.steps("g", "cov", 5, ps.reps(ps.level_of(800))), ps.placed("g")))
def api_place_sites(spark, sf_dir):
    return workspace(spark, sf_dir).place_sites(800).frame(spark)


@query(sql.chain(sql.lattice(100), sql.DIST, sql.TRIPS, sql.DAY_POINTS, ps.members(2, ps.level_radii()[2])) + "SELECT cluster_id, count(DISTINCT path_id) AS n FROM points JOIN member2 USING (node_id) GROUP BY cluster_id")
def api_views(spark, sf_dir):
    workspace(spark, sf_dir).register("ws_")
    return spark.sql("SELECT cluster_id, count(*) AS n FROM ws_cluster_paths WHERE level = 2 GROUP BY cluster_id")


@query(sql.chain(*sql.day_cover()) + "SELECT site_id, CAST(sum(score) AS BIGINT) AS weight FROM cover GROUP BY site_id")
def u_sql_views(spark, sf_dir):
    fx.net100(spark, sf_dir).detours().createOrReplaceTempView("detour_net100")
    udfs.register_sql(spark)
    return spark.sql("SELECT site_id, sum(detour_score(metres, 400)) AS weight FROM detour_net100 WHERE metres <= 400 GROUP BY site_id")
