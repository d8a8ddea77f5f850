"""Mixing sources to target weights by systematic sampling, with DataFrame functions only.

Each source gets a target share of all words. A source whose target is above `max_repeat` times its own words is
held there and the excess goes to the others by weight. Within a source every document's expected copies are
prefix-summed along an order by size; one random offset a source shifts the sum, and a document is taken once for
every integer boundary that its interval crosses.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize, named, pick, text_key, word_count

#: Expected copies are whole multiples of 2^-20, so that prefix sums are exact.
UNIT = 1 << 20
#: Rows of one prefix-sum bucket, about; the number of buckets grows with the source.
BUCKET_ROWS = 1_000


def size_targets(sizes: DataFrame, weights: tuple[float, ...] = (5, 2, 1), max_repeat: int = 3) -> DataFrame:
    """sizes(source, source_size, n_docs) -> the same with target.

    Sources by code point, null last, take the weights in turn. With caps c = max_repeat * size the targets are
    min(c, weight * level); sorted by c / weight the capped sources come first, so running sums give the level.
    One row a source goes through the windows, never documents. A source without words gets 0."""
    everything = Window.partitionBy(F.lit(0))
    # One row a source: the only place where rows meet in one task.
    order = Window.orderBy(F.col("source").isNull(), F.col("source"))
    ranked = sizes.withColumn("weight", F.element_at(F.array(*(F.lit(float(w)) for w in weights)), (F.pmod(F.row_number().over(order) - 1, F.lit(len(weights))) + 1).cast("int")))
    caps = ranked.withColumn("cap", F.col("source_size") * float(max_repeat)).withColumn("fill", F.col("cap") / F.col("weight"))
    by_fill = Window.orderBy("fill", F.col("source").isNull(), "source")
    above = by_fill.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    below = by_fill.rowsBetween(Window.unboundedPreceding, -1)
    levels = caps.withColumn("level", (F.sum("source_size").over(everything) - F.coalesce(F.sum("cap").over(below), F.lit(0.0))) / F.sum("weight").over(above))
    # The first source whose own cap is not reached at its level sets the level of all; capped sources stand before it.
    level = F.min(F.when(F.col("fill") >= F.col("level"), F.struct("fill", F.col("level").alias("level")))).over(everything)["level"]
    found = levels.withColumn("common", level)
    target = F.when(F.col("common").isNull() | (F.col("cap") <= F.col("weight") * F.col("common")), F.col("cap")).otherwise(F.col("weight") * F.col("common"))
    return found.select("source", "source_size", "n_docs", target.alias("target"))


def random_key(column: Column, salt: str) -> Column:
    """60 pseudo-random bits of a value, equal on every run and in every engine that has MD5."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{salt}:"), F.coalesce(column.cast("string"), F.lit("\x00")))), 1, 15), 16, 10).cast("long")


def mix_sources(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: tuple[float, ...] = (5, 2, 1), max_repeat: int = 3, seed: str = "mix") -> DataFrame:
    """docs -> (doc_id, tkey, source, size, source_size, target, copies, taken) for every input row.

    size: words of the text. copies: how often the mix takes the row (0 to max_repeat); taken = copies * size.
    Null and empty texts have size 0; they share the copies of their source but add no words. A null source is a
    source of its own, last in order. Repeated rows are rows of their own. tkey is xxhash64 of the text. Empty input: no
    rows.

    No task holds a source: rows are dealt into buckets along (size class, hash), bucket totals are prefix-summed
    (one row per BUCKET_ROWS documents, in two steps), and rows are summed within their bucket only."""
    rows = pick(docs, doc_id=id_col, text=text_col, source=source_col).select("doc_id", "source", text_key(F.col("text")).alias("tkey"), word_count(F.col("text")).alias("size"))
    # Classes are powers of two of the size; ties and repeated rows are told apart by the text-free key and row order.
    rows = materialize(rows.withColumn("key", random_key(F.col("doc_id"), seed)).withColumn("class", F.length(F.bin(F.col("size")))), "mix-sizes")
    groups = rows.groupBy("source", "class").agg(F.count("*").alias("n"), F.sum("size").alias("words"))
    sources = groups.groupBy("source").agg(F.sum("words").alias("source_size"), F.sum("n").alias("n_docs"))
    targets = size_targets(sources, weights, max_repeat)
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    offset = F.pmod(random_key(F.col("source"), f"{seed}-offset"), F.lit(UNIT))
    goal = targets.select(F.col("source").alias("of"), "source_size", "target", F.round(rate * UNIT).cast("long").alias("step"), offset.alias("offset"))
    plan = groups.select(F.col("source").alias("in"), F.col("class").alias("of_class"), F.ceil(F.col("n") / BUCKET_ROWS).cast("long").alias("parts"))
    plan = plan.join(goal, F.col("in").eqNullSafe(F.col("of"))).drop("of")
    dealt = rows.join(plan, F.col("source").eqNullSafe(F.col("in")) & (F.col("class") == F.col("of_class"))).drop("in", "of_class").withColumn("part", F.pmod("key", "parts"))
    totals = dealt.groupBy("source", "class", "part").agg(F.sum("step").alias("sum"))
    # Buckets are summed in stretches of BUCKET_ROWS, and stretches before them.
    totals = totals.withColumn("stretch", F.floor(F.col("part") / BUCKET_ROWS))
    long = totals.groupBy("source", "class", "stretch").agg(F.sum("sum").alias("long"))
    before_long = Window.partitionBy("source").orderBy("class", "stretch").rowsBetween(Window.unboundedPreceding, -1)
    ahead = long.select(F.col("source").alias("in"), F.col("class").alias("of_class"), F.col("stretch").alias("of_stretch"), F.coalesce(F.sum("long").over(before_long), F.lit(0)).alias("ahead"))
    before = Window.partitionBy("source", "class", "stretch").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    near = totals.join(ahead, F.col("source").eqNullSafe(F.col("in")) & (F.col("class") == F.col("of_class")) & (F.col("stretch") == F.col("of_stretch")))
    starts = near.select(F.col("source").alias("in"), F.col("class").alias("of_class"), F.col("part").alias("of_part"), (F.col("ahead") + F.coalesce(F.sum("sum").over(before), F.lit(0))).alias("start"))
    joined = dealt.join(starts, F.col("source").eqNullSafe(F.col("in")) & (F.col("class") == F.col("of_class")) & (F.col("part") == F.col("of_part")))
    upper = F.col("start") + F.col("offset")
    inside = Window.partitionBy("source", "class", "part").orderBy("size", "key", "doc_id", "tkey").rowsBetween(Window.unboundedPreceding, 0)
    summed = joined.withColumn("upper", upper + F.sum("step").over(inside))
    copies = F.floor(F.col("upper") / UNIT) - F.floor((F.col("upper") - F.col("step")) / UNIT)
    return summed.withColumn("copies", copies.cast("long")).select("doc_id", "tkey", "source", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"))


def mix_rows(docs: DataFrame, **options) -> DataFrame:
    """The mixed corpus itself: each row of docs, with all its columns, as often as the mix takes it.

    Rows that share id, text and source are equal to the mix: together they are taken as often as their plan rows are, each
    of them as often as the others or once more."""
    id_col, text_col, source_col = options.get("id_col", "doc_id"), options.get("text_col", "text"), options.get("source_col", "source")
    plan = mix_sources(docs, **options)
    whole = plan.groupBy("doc_id", "tkey", "source").agg(F.sum("copies").alias("copies"), F.count("*").alias("n")).where("copies > 0")
    whole = whole.select(F.struct("doc_id", "tkey", "source").alias("of"), "copies", "n")
    own = F.struct(named(docs, id_col).alias("doc_id"), text_key(named(docs, text_col)).alias("tkey"), named(docs, source_col).alias("source"))
    held = docs.select(F.struct(*(named(docs, c) for c in docs.columns)).alias("row"), own.alias("own"))
    # A struct of nulls equals another, so plain equality will do, and rows stay where the join has put them.
    joined = held.join(whole, held["own"] == whole["of"])
    place = F.row_number().over(Window.partitionBy("own").orderBy(F.xxhash64(F.col("row"))))
    taken = joined.select("row", (F.floor(F.col("copies") / F.col("n")) + (place <= F.pmod("copies", "n")).cast("long")).alias("copies"))
    return taken.where("copies > 0").withColumn("copy", F.explode(F.array_repeat(F.lit(0), F.col("copies").cast("int")))).select("row.*")
