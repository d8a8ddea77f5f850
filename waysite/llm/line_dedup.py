"""Line deduplication by an exact set-similarity join, with DataFrame and SQL functions only.

A line is the set of its words. Words are ordered from rare to frequent; two sets at Jaccard `share` or more then have
a word in common in their prefixes. Equal lines are one before anything is joined. Lines meet over prefix words and
pass filters of length, position and of a 64-bit parity map of their words (no two sets that differ in fewer words
can differ in more bits); only then are they verified on their whole text. Over a word that very many lines hold in
their prefix, lines first meet the earliest one alone; those that match nothing there then meet all the others."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import discard, materialize, named, pick, text_key

#: Counters of the word-frequency sketch: a fixed size. Collisions change the order of words, never a result.
SLOT_BITS = 19
#: A prefix word held by more lines than this is met in two steps.
MANY = 256
#: Long sets differ in more words than 64 bits can tell: from this size on, lines have a parity map of 256 bits too.
LONG_SET = 112
MAP = ("m0", "m1", "m2")
#: Lines with fewer distinct words always stay: by default only those without any.
LEAST_WORDS = 1
#: Words of the candidate filter at most, 64 bits each.
MOST_FILTER_WORDS = 1 << 20
HASH_MASK = (1 << 54) - 1


def line_rows(docs: DataFrame) -> DataFrame:
    """docs(doc_id, text, tkey) -> (doc_id, tkey, line_no, line, lkey): the lines in lower case with spaces for other white
    space, as their words are compared; a null text is one empty line."""
    low = F.lower(F.coalesce("text", F.lit("")))
    plain = F.when(low.rlike("[\\x09\\x0b\\x0c\\x0d]"), F.translate(low, "\t\x0b\x0c\r", "    ")).otherwise(low)
    cut = docs.select("doc_id", "tkey", F.posexplode(F.split(plain, "\n")).alias("line_no", "line"))
    return cut.withColumn("lkey", F.xxhash64("line"))


def word_hashes(line: str) -> Column:
    """Distinct words of a line as 64-bit hashes."""
    return F.expr(f"array_remove(array_distinct(transform(split({line}, ' '), w -> xxhash64(w))), xxhash64(''))")


def word_keys(line: str, ranks: str) -> Column:
    """Distinct words of a line as 64-bit keys in the order of rarity: nine bits of rank, then bits of the hash. ranks
    holds the rank of each slot in its place in the key."""
    # ranks stands here once only: a column that stands twice is not inlined, and every row would carry the array.
    key = f"get({ranks}, shiftrightunsigned(t, {64 - SLOT_BITS})) | (t & {HASH_MASK}L)"
    return F.expr(f"sort_array(array_distinct(transform(array_remove(transform(split({line}, ' '), w -> xxhash64(w)), xxhash64('')), t -> {key})))")


def frequency_ranks(lines: DataFrame) -> DataFrame:
    """One row, one array: for each slot the rank (0 to 511, logarithmic) of how often its words occur in all lines, in
    its place in a key.

    Counts are summed per task before they are shuffled; the array has 2^SLOT_BITS entries at any size of corpus."""
    slots = lines.select(F.explode(F.split("line", " ")).alias("w")).select(F.expr(f"shiftrightunsigned(xxhash64(w), {64 - SLOT_BITS})").alias("slot"))
    counted = slots.groupBy("slot").agg(F.count("*").alias("c"))
    filled = lines.sparkSession.range(0, 1 << SLOT_BITS, 1, 8).select(F.col("id").alias("slot"), F.lit(0).cast("long").alias("c")).unionByName(counted)
    rank = F.least(F.floor(16 * F.log2(F.col("c") + F.lit(1.0))), F.lit(511)).cast("long")
    whole = filled.groupBy("slot").agg(F.sum("c").alias("c")).select("slot", F.shiftleft(rank, 54).alias("rank"))
    return whole.agg(F.expr("transform(array_sort(collect_list(struct(slot, rank))), x -> x.rank)").alias("ranks"))


def prefix_of(keys: str, share: int) -> Column:
    """The first n - ceil(share * n) + 1 words of a sorted set, as 32-bit hashes: that two words may then look equal
    only adds candidates."""
    return F.expr(f"transform(slice({keys}, 1, cast(size({keys}) - ({share} * size({keys}) + 99) div 100 + 1 as int)), t -> hash(t))")


def compatible(a: str, b: str, share: int) -> Column:
    """Length, position and parity filters for rows a and b (n, pos, bits, m0..m2) that share a prefix word. bits is
    the fold of the wide map m0..m3, which short lines don't have."""
    n1, n2, i, j = (F.col(f"{x}.{c}") for c, x in (("n", a), ("n", b), ("pos", a), ("pos", b)))
    words = [F.col(f"{a}.{c}").bitwiseXOR(F.col(f"{b}.{c}")) for c in ("bits", "m0", "m1", "m2")]
    words.append(words[0].bitwiseXOR(words[1]).bitwiseXOR(words[2]).bitwiseXOR(words[3]))  # the fourth word of the map
    wide = sum((F.bit_count(w) for w in words[2:]), F.bit_count(words[1])) * (100 + share) <= (100 - share) * (n1 + n2)
    length = 100 * F.least(n1, n2) >= share * F.greatest(n1, n2)
    position = (F.least(i, j) + 1 + F.least(n1 - 1 - i, n2 - 1 - j)) * (100 + share) >= share * (n1 + n2)
    parity = F.bit_count(F.col(f"{a}.bits").bitwiseXOR(F.col(f"{b}.bits"))) * (100 + share) <= (100 - share) * (n1 + n2)
    return length & position & parity & F.coalesce(wide, F.lit(True))


def filter_words(keys: DataFrame, words: int) -> DataFrame:
    """One row, one array of `words` 64-bit words: the bits of pmod(lkey, 64 * words) that are set."""
    marked = keys.select(F.expr(f"pmod(lkey, {64 * words}L)").alias("at")).select(F.expr("at div 64").alias("word"), F.expr("shiftleft(1L, cast(at % 64 as int))").alias("bit"))
    filled = marked.unionByName(keys.sparkSession.range(0, words, 1, 4).select(F.col("id").alias("word"), F.lit(0).cast("long").alias("bit")))
    whole = filled.groupBy("word").agg(F.bit_or("bit").alias("bits"))
    return whole.agg(F.expr("transform(array_sort(collect_list(struct(word, bits))), x -> x.bits)").alias("held"))


def marked_lines(rows: DataFrame, wanted: DataFrame) -> DataFrame:
    """The lines of rows whose key is one of wanted(lkey), and few others: a bit filter of a bounded size thins them
    before they are shuffled."""
    words = 1 << max(4, min(MOST_FILTER_WORDS, wanted.count() // 4 + 1).bit_length())
    held = materialize(filter_words(wanted, words), "line-filter")
    at = f"pmod(lkey, {64 * words}L)"
    lines = line_rows(rows).withColumn("held", held.select("held").scalar())
    return lines.where(F.expr(f"(get(held, {at} div 64) & shiftleft(1L, cast({at} % 64 as int))) <> 0")).drop("held")


def verify(rows: DataFrame, pairs: DataFrame, distinct: DataFrame, share: int) -> DataFrame | None:
    """pairs(a, b) of line ids -> those at Jaccard share / 100 or more, by the words of their whole text; None: no pairs."""
    pairs = materialize(pairs, "line-pairs")
    if pairs.isEmpty():
        discard(pairs)
        return None
    ids = pairs.select(F.col("a").alias("i")).unionByName(pairs.select(F.col("b").alias("i"))).distinct()
    wanted = materialize(distinct.select("id", "lkey").join(ids, F.col("id") == F.col("i")).select("id", "lkey"), "line-wanted")
    lines = marked_lines(rows, wanted).select("lkey", "line").dropDuplicates(["lkey"])
    sets = materialize(lines.join(wanted, "lkey").select("id", word_hashes("line").alias("words")), "line-sets")
    left, right = sets.select(F.col("id").alias("k1"), F.col("words").alias("w1")), sets.select(F.col("id").alias("k2"), F.col("words").alias("w2"))
    both = pairs.join(left, F.col("a") == F.col("k1")).join(right, F.col("b") == F.col("k2"))
    common = F.size(F.array_intersect("w1", "w2"))
    matched = materialize(both.where(100 * common >= share * (F.size("w1") + F.size("w2") - common)).select("a", "b"), "line-matches")
    discard(pairs, wanted, sets)
    return matched


def later_of(pairs: DataFrame, distinct: DataFrame) -> DataFrame:
    """(id): of each matching pair the line whose first place is later."""
    place = distinct.select(F.col("id").alias("k"), "first")
    one = pairs.join(place, F.col("a") == F.col("k")).select("a", "b", F.col("first").alias("fa"))
    two = one.join(place, F.col("b") == F.col("k")).select("a", "b", "fa", F.col("first").alias("fb"))
    return two.select(F.when(F.col("fa") < F.col("fb"), F.col("b")).otherwise(F.col("a")).alias("id")).distinct()


def removed_lines(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", share: int = 80, least_words: int = LEAST_WORDS) -> DataFrame:
    """docs -> (doc_id, tkey, n_lines, removed): for every document its number of lines and the places (from 0) of the
    lines that go, ascending.

    A line goes if an earlier line, by (doc_id with nulls first, text key, place), has a set of words at Jaccard
    share / 100 or more with its own, whether or not that line stays itself. Lines with fewer than least_words distinct
    words stay. Rows that repeat both id and text are one document. Empty and null texts are one empty line. tkey is
    xxhash64 of the text. Words and lines are compared as 64-bit hashes."""
    rows = pick(docs, doc_id=id_col, text=text_col).withColumn("tkey", text_key(F.col("text")))
    lines = line_rows(rows)
    ranks = materialize(frequency_ranks(lines), "line-ranks")
    # A filter on the keys would be computed before them, from all over again; lines without a word are told by their text.
    keyed = lines.where(F.trim("line") != "").withColumn("ranks", ranks.select("ranks").scalar()).select("doc_id", "tkey", "line_no", "lkey", word_keys("line", "ranks").alias("keys"))
    shaped = keyed.select("lkey", F.xxhash64("keys").alias("skey"), F.struct("doc_id", "tkey", "line_no").alias("place"), F.size("keys").alias("n"), F.expr("aggregate(keys, 0L, (a, t) -> a ^ shiftleft(1L, cast(t & 63 as int)))").alias("bits"), *(F.expr(f"CASE WHEN size(keys) >= {LONG_SET} THEN aggregate(filter(keys, t -> (t & 192) = {64 * k}), 0L, (a, t) -> a ^ shiftleft(1L, cast(t & 63 as int))) END").alias(f"m{k}") for k in range(3)), prefix_of("keys", share).alias("prefix"))
    grouped = shaped.groupBy("lkey").agg(F.min("place").alias("first"), F.count("*").alias("copies"), F.first("skey").alias("skey"), F.first("n").alias("n"), F.first("bits").alias("bits"), *(F.first(m).alias(m) for m in MAP), F.first("prefix").alias("prefix"))
    # The table is written once, so the numbers given here stay; they are short, and neighbours have like ones.
    distinct = materialize(grouped.where(F.col("n") >= least_words).withColumn("id", F.monotonically_increasing_id()), "line-distinct")
    # A set of fewer than share / (100 - share) words is like no other set: such lines are grouped, not joined.
    large = -(-share // max(1, 100 - share))
    small = distinct.where(F.col("n") < large)
    earliest = small.groupBy("skey").agg(F.min("first").alias("least"), F.count("*").alias("lines")).where("lines > 1").select(F.col("skey").alias("s"), "least")
    equal = small.join(earliest, F.col("skey") == F.col("s")).where(F.col("first") != F.col("least")).select("id")
    joined = distinct.where(F.col("n") >= large)
    entries = joined.select("id", "n", "bits", *MAP, F.posexplode("prefix").alias("pos", "word"))
    # The place packed into a number only picks hubs; what is earlier is decided by the place itself.
    at = F.expr("((coalesce(try_cast(first.doc_id as bigint), 0L) & 1099511627775L) << 20) | least(first.line_no, 1048575)")
    counts = joined.select("id", at.alias("at"), F.explode("prefix").alias("word")).groupBy("word").agg(F.count("*").alias("c"), F.min_by("id", "at").alias("hub"))
    many = materialize(counts.where(F.col("c") > MANY).select(F.col("word").alias("w"), "hub"), "line-many")
    marked = entries.join(many, F.col("word") == F.col("w"), "left").select("word", "id", "n", "pos", "bits", *MAP, "hub")
    # Both sides read the same columns, so Spark shuffles the entries once for both.
    a, b = marked.alias("a"), marked.alias("b")
    once = (F.col("a.hub").isNull() & F.col("b.hub").isNull() & (F.col("a.id") < F.col("b.id"))) | ((F.col("b.id") == F.col("b.hub")) & (F.col("a.id") != F.col("b.id")))
    met = a.join(b, (F.col("a.word") == F.col("b.word")) & once & compatible("a", "b", share)).select(F.least("a.id", "b.id").alias("a"), F.greatest("a.id", "b.id").alias("b")).distinct()
    none = rows.sparkSession.createDataFrame([], "id long")
    matched = verify(rows, met, distinct, share)
    gone = none if matched is None else materialize(later_of(matched, distinct), "line-gone")
    # Lines not yet matched meet every line with which they share such a word.
    crowded = entries.join(many, F.col("word") == F.col("w")).select("word", "id", "n", "pos", "bits", *MAP)
    open_lines = crowded.join(gone, "id", "left_anti").alias("a")
    rest = open_lines.join(crowded.alias("b"), (F.col("a.word") == F.col("b.word")) & (F.col("a.id") != F.col("b.id")) & compatible("a", "b", share)).select(F.least("a.id", "b.id").alias("a"), F.greatest("a.id", "b.id").alias("b")).distinct()
    more = verify(rows, rest, distinct, share)
    also = none if more is None else later_of(more, distinct)
    # Only lines that match or repeat can go; the others are not looked at again.
    found = distinct.select("id", "lkey", "first", "copies").join(gone.unionByName(also).unionByName(equal).distinct().select(F.col("id").alias("g")), F.col("id") == F.col("g"), "left")
    judged = materialize(found.where(F.col("g").isNotNull() | (F.col("copies") > 1)).select("lkey", "first", F.col("g").isNotNull().alias("matched")), "line-judged")
    discard(ranks, distinct, many, *(t for t in (matched, more) if t is not None), *([gone] if matched is not None else []))
    placed = marked_lines(rows, judged).select("doc_id", "tkey", "line_no", F.col("lkey").alias("k")).join(judged, F.col("lkey") == F.col("k"))
    goes = placed.where(F.col("matched") | (F.struct("doc_id", "tkey", "line_no") != F.col("first"))).select("doc_id", "tkey", F.lit(None).cast("int").alias("n_lines"), "line_no")
    # Its number of lines stands for a document of which none goes.
    whole = rows.select("doc_id", "tkey", F.size(F.split(F.coalesce("text", F.lit("")), "\n")).alias("n_lines"), F.lit(None).cast("int").alias("line_no"))
    return whole.unionByName(goes).groupBy("doc_id", "tkey").agg(F.max("n_lines").cast("long").alias("n_lines"), F.array_sort(F.collect_set("line_no")).alias("removed"))


def drop_lines(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", share: int = 80, least_words: int = LEAST_WORDS) -> DataFrame:
    """docs with the removed lines cut out of the text, all columns kept; documents left without any word, which had
    one before, go."""
    removed = removed_lines(docs, id_col=id_col, text_col=text_col, share=share, least_words=least_words).where(F.size("removed") > 0).select(F.struct("doc_id", "tkey").alias("of"), "removed")
    text = named(docs, text_col)
    here = F.struct(named(docs, id_col).alias("doc_id"), text_key(text).alias("tkey"))
    joined = docs.join(removed, here == removed["of"], "left")
    gone = removed["removed"]
    kept = F.filter(F.split(text, "\n"), lambda _, i: ~F.array_contains(gone, i))
    cut = F.when(gone.isNull(), text).otherwise(F.array_join(kept, "\n"))
    empty = gone.isNotNull() & ~cut.rlike("[^\\x20\\x09-\\x0D]")
    return joined.where(~F.coalesce(empty, F.lit(False))).select(*(cut.alias(c) if c == text_col else named(docs, c) for c in docs.columns))
