"""The relations of the engine and the columns they must have."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import types as T

NODE = T.StructType([T.StructField("node_id", T.LongType()), T.StructField("x", T.IntegerType()), T.StructField("y", T.IntegerType())])
EDGE = T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType()), T.StructField("metres", T.IntegerType())])
PATH_POINT = T.StructType([T.StructField("path_id", T.LongType()), T.StructField("seq", T.IntegerType()), T.StructField("node_id", T.LongType()), T.StructField("ts", T.TimestampType())])
SITE = T.StructType([T.StructField("site_id", T.LongType()), T.StructField("cost", T.DoubleType()), T.StructField("capacity", T.LongType()), T.StructField("existing", T.BooleanType())])
DISTANCE = T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType()), T.StructField("metres", T.LongType())])
DETOUR = T.StructType([T.StructField("path_id", T.LongType()), T.StructField("site_id", T.LongType()), T.StructField("metres", T.LongType())])
COVER = T.StructType([*DETOUR.fields, T.StructField("score", T.LongType())])

#: The given tables, with the columns read from each.
TABLES = {
    "events": "event_id long, ts timestamp, user_id long, event_type string, value double, props string",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp, o_orderpriority string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_returnflag string, l_linestatus string, l_shipdate timestamp",
}


def require(df: DataFrame, schema: T.StructType) -> DataFrame:
    """The columns of schema, cast to its types; an error names what is missing."""
    missing = [f.name for f in schema if f.name not in df.columns]
    if missing:
        raise ValueError(f"columns missing: {', '.join(missing)}")
    return df.select(*(df[f.name].cast(f.dataType).alias(f.name) for f in schema))
