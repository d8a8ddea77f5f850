"""Near-duplicate documents by an exact n-gram Jaccard join with grouped prefixes.

A document is its set of word shingles. In an order from rare to frequent, two sets at Jaccard `share` or more have a
token in common within the first tenths of both, their prefixes. Equal sets are one node; nodes with equal prefixes
and sizes are one group. Groups meet over the tokens of their prefixes, are filtered by size and position, and only then expand
to their nodes, which are verified on the whole texts.

Components need not see every pair of a large group of copies: over each token all groups first meet one hub, and
nodes joined that way need not meet again. What is left, pairs of different components, is then met exhaustively."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import discard, materialize, mix64, named, pick, segments, slices, text_key, utf8_buffer, word_stream
from .graph import connected_components

SLICE = 2 << 20
#: Counters of the frequency sketch, and in how many parts they are summed. Fixed size; collisions only change the order.
SLOTS, SLOT_PARTS = 1 << 23, 64
#: Bits of a set's parity map: two sets differ in at least as many members as their maps differ in bits. Its
#: fold to 64 bits goes with every prefix token, the whole map with every pair of sets.
PARITY_WORDS = 8
#: A token in the prefixes of more groups than this is met in two steps.
MANY = 64
#: Bits of the filter for texts to verify: 64 a candidate, at most this many (16 MB).
MOST_BITS = 1 << 27


def shingle_hashes(array: pa.Array, width: int) -> list[np.ndarray]:
    """For each text its distinct shingles as sorted 64-bit hashes; fewer words than width: the whole sequence."""
    stream = word_stream(*utf8_buffer(array), lower=True)
    words, ends = segments(stream)
    coded = pc.dictionary_encode(words)
    own = np.fromiter((xxhash.xxh3_64_intdigest(w) for w in coded.dictionary.to_pylist()), np.uint64, len(coded.dictionary))
    word = own[np.asarray(coded.indices)]
    stops = np.flatnonzero(ends)
    rolled = mix64(word)
    for k in range(1, width):
        rolled = mix64(rolled[: len(word) - k] + word[k:]) if len(word) > k else rolled[:0]
    out, start = [], 0
    for stop in stops.tolist():
        n = stop - start
        if n >= width:
            out.append(np.unique(rolled[start : stop - width + 1]))
        elif n:
            h = np.uint64(n)
            for w in word[start:stop]:
                h = mix64(np.array([h]) + w)[0]
            out.append(np.array([h], np.uint64))
        else:
            out.append(np.zeros(0, np.uint64))
        start = stop + 1
    return out


def slot_counts(docs: DataFrame, width: int) -> np.ndarray:
    """How many texts hold a shingle of each slot, over all texts, as ranks 0 to 255 on a logarithmic scale."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(SLOTS, np.uint32)
        for batch in slices(batches, "text", SLICE):
            found = shingle_hashes(batch.column(0), width)
            if found:
                at, times = np.unique(np.concatenate(found) & np.uint64(SLOTS - 1), return_counts=True)
                total[at.astype(np.int64)] += times.astype(np.uint32)
        for part, values in enumerate(np.split(total, SLOT_PARTS)):
            if values.any():
                yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([zstandard.compress(values.tobytes(), 1)], pa.binary())], names=["part", "counts"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        totals: dict[int, np.ndarray] = {}
        for batch in batches:
            for part, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                totals[part] = totals.get(part, 0) + np.frombuffer(zstandard.decompress(data), "<u4").astype("<i8")
        for part, values in totals.items():
            ranks = np.minimum(8 * np.log2(values + 1), 255).astype(np.uint8)
            yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([zstandard.compress(ranks.tobytes(), 1)], pa.binary())], names=["part", "counts"])

    counted = docs.select("text").mapInArrow(count, "part int, counts binary")
    summed = counted.repartition(SLOT_PARTS, "part").mapInArrow(add, "part int, counts binary").collect()  # SLOTS bytes at most
    total = np.zeros((SLOT_PARTS, SLOTS // SLOT_PARTS), np.uint8)
    for part, data in summed:
        total[part] = np.frombuffer(zstandard.decompress(data), np.uint8)
    return total.reshape(-1)


def prefix_length(n: int, share: int) -> int:
    return n - -(-share * n // 100) + 1


def prefixes(docs: DataFrame, ranks, width: int, share: int) -> DataFrame:
    """docs(doc_id, text, tkey) -> (doc_id, tkey, n, sig, gid, hot, parity, prefix): sig: the set, 16 bytes (null:
    empty set); gid: prefix and size; hot: mean rank of the prefix; parity: for each of the map's bits whether an odd
    number of members falls on it; prefix: its tokens from rare to frequent."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rank = ranks.value
        for batch in slices(batches, "text", SLICE):
            sizes, sigs, gids, hots, parities, tokens = [], [], [], [], [], []
            for found in shingle_hashes(batch.column(1), width):
                n = len(found)
                sizes.append(n)
                if not n:
                    for column, value in ((sigs, None), (gids, 0), (hots, 0), (parities, []), (tokens, [])):
                        column.append(value)
                    continue
                sigs.append(xxhash.xxh3_128_digest(found.tobytes()))
                ordered = np.sort(rank[(found & np.uint64(SLOTS - 1)).astype(np.int64)].astype(np.uint64) << np.uint64(56) | found >> np.uint64(8))
                first = ordered[: prefix_length(n, share)]
                gids.append(int(np.array(xxhash.xxh3_64_intdigest(first.tobytes(), seed=n), np.uint64).view(np.int64)))
                hots.append(int((first >> np.uint64(56)).mean()))
                odd = np.bincount((found >> np.uint64(24)).astype(np.int64) & (64 * PARITY_WORDS - 1), minlength=64 * PARITY_WORDS) & 1
                parities.append(np.packbits(odd.astype(bool), bitorder="little").view("<i8"))
                tokens.append(first.view(np.int64))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(sizes, pa.int64()), pa.array(sigs, pa.binary()), pa.array(gids, pa.int64()), pa.array(hots, pa.int32()), pa.array(parities, pa.list_(pa.int64())), pa.array(tokens, pa.list_(pa.int64()))], names=["doc_id", "tkey", "n", "sig", "gid", "hot", "parity", "prefix"])

    return docs.select("doc_id", "text", "tkey").mapInArrow(run, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, tkey long, n long, sig binary, gid long, hot int, parity array<long>, prefix array<long>")


def compatible(one: str, two: str, share: int) -> Column:
    """Size, position and parity filters for two sets that share a token; one and two end the names of their columns
    n, pos and bits. Groups of several sets have null bits, which filter nothing."""
    a, b, i, j, x, y = (F.col(f"{c}{k}") for c in ("n", "pos", "bits") for k in (one, two))
    reach = F.least(i, j) + 1 + F.least(a - 1 - i, b - 1 - j)
    parity = F.bit_count(x.bitwiseXOR(y)) * (100 + share) <= (100 - share) * (a + b)
    return (100 * F.least(a, b) >= share * F.greatest(a, b)) & (reach * (100 + share) >= share * (a + b)) & F.coalesce(parity, F.lit(True))


def candidate_texts(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """(tkey, text), one row a key of wanted(tkey), compressed, written once. A bit filter of bounded size thins the
    texts before the shuffle."""
    n = wanted.count()
    bits = 1 << max(10, min(MOST_BITS, 64 * max(1, n)).bit_length() - 1)

    def mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = np.zeros(bits, bool)
        for batch in batches:
            held[np.asarray(batch.column(0)) & (bits - 1)] = True
        if held.any():
            yield pa.RecordBatch.from_arrays([pa.array([zstandard.compress(np.packbits(held).tobytes(), 1)], pa.binary())], names=["bits"])

    parts = wanted.coalesce(8).mapInArrow(mark, "bits binary").collect()  # eight filters of at most MOST_BITS
    held = np.zeros(bits // 8, np.uint8)
    for (data,) in parts:
        held |= np.frombuffer(zstandard.decompress(data), np.uint8)
    shared = docs.sparkSession.sparkContext.broadcast(held)

    def thin(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = np.unpackbits(shared.value).astype(bool)
        for batch in batches:
            left = batch.filter(pa.array(known[np.asarray(batch.column(0)) & (bits - 1)]))
            packed = [zstandard.compress((t or "").encode(), 3) for t in left.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([left.column(0), pa.array(packed, pa.binary())], names=["tkey", "text"])

    thinned = docs.select("tkey", "text").mapInArrow(thin, "tkey long, text binary")
    texts = materialize(thinned.join(wanted.select(F.col("tkey").alias("k")), F.col("tkey") == F.col("k")).drop("k").dropDuplicates(["tkey"]), "shingle-texts")
    shared.destroy()
    return texts


def verified(docs: DataFrame, pairs: DataFrame, nodes: DataFrame, width: int, share: int) -> DataFrame:
    """pairs(a, b) of nodes -> those that link, by intersection and union of their whole sets."""
    keys = nodes.select(F.col("sig").alias("of"), "tkey", "n", "parity")
    left = pairs.join(keys, F.col("a") == F.col("of")).select("a", "b", F.col("tkey").alias("ka"), F.col("n").alias("na"), F.col("parity").alias("xa"))
    keyed = left.join(keys, F.col("b") == F.col("of")).withColumn("apart", F.aggregate(F.zip_with("xa", "parity", lambda p, q: F.bit_count(p.bitwiseXOR(q))), F.lit(0), lambda t, v: t + v))
    near = (F.col("apart") * (100 + share) <= (100 - share) * (F.col("na") + F.col("n"))) & (100 * F.least("na", "n") >= share * F.greatest("na", "n"))
    keyed = keyed.where(near).select("a", "b", "ka", F.col("tkey").alias("kb"))
    keyed = materialize(keyed, "shingle-pairs")
    wanted = keyed.select(F.col("ka").alias("tkey")).unionByName(keyed.select(F.col("kb").alias("tkey"))).distinct()
    texts = candidate_texts(docs, wanted)
    left = texts.select(F.col("tkey").alias("t1"), F.col("text").alias("ta"))
    right = texts.select(F.col("tkey").alias("t2"), F.col("text").alias("tb"))
    joined = keyed.join(left, F.col("ka") == F.col("t1")).join(right, F.col("kb") == F.col("t2")).select("a", "b", "ka", "kb", "ta", "tb")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, np.ndarray] = {}
        for whole in slices(batches, "ta", SLICE // 4):
            for batch in slices([whole], "tb", SLICE // 4):
                sets = []
                for key, text in ((2, 4), (3, 5)):
                    ids = batch.column(key).to_pylist()
                    fresh = {k: i for i, k in enumerate(ids) if k not in held}
                    if len(held) + len(fresh) > 1000:
                        held.clear()
                        fresh = {k: i for i, k in enumerate(ids)}
                    plain = [zstandard.decompress(batch.column(text)[i].as_py()).decode() for i in fresh.values()]
                    held.update(zip(fresh, shingle_hashes(pa.array(plain, pa.large_string()), width), strict=True))
                    sets.append([held[k] for k in ids])
                links = []
                for x, y in zip(*sets, strict=True):
                    common = len(np.intersect1d(x, y, assume_unique=True))
                    links.append(100 * common >= share * (len(x) + len(y) - common))
                yield batch.select(["a", "b"]).filter(pa.array(links, pa.bool_()))

    links = materialize(joined.mapInArrow(run, "a binary, b binary"), "shingle-links")
    discard(keyed, texts)
    return links


def expand_to_nodes(pairs: DataFrame, nodes: DataFrame, left: str, right: str) -> DataFrame:
    return pairs.join(nodes.select(F.col("gid").alias("g"), F.col("sig").alias("b")), F.col(right) == F.col("g")).select(F.col(left).alias("a"), "b")


def near_components(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", width: int = 3, share: int = 90) -> DataFrame:
    """docs -> (doc_id, tkey, n_shingles, component_id, n_linked, root), a row for every input row.

    Two documents link when 100 * |intersection| >= share * |union| of their `width`-word shingle sets (A-Z lower-cased;
    with fewer words the whole sequence is the one shingle). component_id: the smallest doc_id reachable by links,
    itself included; documents without words or text (null) link with nothing. n_linked: documents of the component;
    tkey: a hash of the row's text; root: the component itself, whatever its ids (null: no words). Null ids never name a
    component that has another id; repeated rows are equal sets. Sets are compared as 64-bit hashes of shingles."""
    # Whole texts; equal texts have equal keys, which name the text to verify a set on.
    rows = pick(docs, doc_id=id_col, text=text_col).withColumn("tkey", text_key(F.col("text")))
    ranks = rows.sparkSession.sparkContext.broadcast(slot_counts(rows, width))
    found_prefixes = materialize(prefixes(rows, ranks, width, share), "shingle-prefixes")
    ranks.destroy()
    found = materialize(found_prefixes.select("doc_id", "tkey", "n", "sig"), "shingle-sets")
    nodes = materialize(found_prefixes.where("n > 0").groupBy("sig").agg(F.min("tkey").alias("tkey"), F.first("gid").alias("gid"), F.first("n").alias("n"), F.first("parity").alias("parity"), F.count("*").alias("copies")), "shingle-nodes")
    word = reduce(lambda x, y: x.bitwiseXOR(y), [F.col("parity")[k] for k in range(PARITY_WORDS)])  # the map modulo 64
    groups = found_prefixes.where("n > 0").groupBy("gid").agg(F.first("n").alias("n"), F.when(F.min(word) == F.max(word), F.min(word)).alias("bits"), F.first("hot").alias("hot"), F.count("*").alias("weight"), F.first("prefix").alias("prefix"))
    # One number ranks groups as hubs: many copies first, then frequent prefixes (an original has no rare edits of its own).
    rank = F.shiftleft(F.least(F.col("weight"), F.lit(65535)), 46) + F.shiftleft(F.col("hot").cast("long"), 38) + F.pmod("gid", F.lit(1 << 38))
    entries = groups.select("gid", "n", "bits", rank.alias("rank"), F.posexplode("prefix").alias("pos", "token"))
    # Counts and the highest rank of each token are pre-aggregated as whole numbers; most tokens occur once and end here.
    shared = entries.groupBy("token").agg(F.count("*").alias("c"), F.max("rank").alias("top")).where("c > 1").withColumnRenamed("token", "t")
    met = materialize(entries.join(shared, F.col("token") == F.col("t")).drop("t"), "shingle-met")
    discard(found_prefixes)
    hubs = met.where("rank = top").select(F.col("token").alias("t"), F.col("gid").alias("hub"), F.col("n").alias("n_h"), F.col("pos").alias("pos_h"), F.col("bits").alias("bits_h"))
    meeting = materialize(met.join(hubs, F.col("token") == F.col("t")).drop("t", "rank", "top"), "shingle-meeting")
    discard(met)
    group_pairs = meeting.where((F.col("gid") != F.col("hub")) & compatible("", "_h", share)).select(F.col("hub").alias("h"), "gid").distinct()
    # Written, so that a join with it stands between two shuffles and a group of very many nodes can be split over tasks.
    lead = materialize(nodes.groupBy("gid").agg(F.min("sig").alias("lead"), F.count("*").alias("n_nodes")), "shingle-lead")
    # The hub group's first node meets all nodes of the other groups, and every group's first node its own others.
    starred = group_pairs.join(lead.select(F.col("gid").alias("g"), "lead"), F.col("h") == F.col("g")).select("lead", "gid")
    own = lead.where("n_nodes > 1").select("lead", "gid")
    star = expand_to_nodes(starred.unionByName(own), nodes, "lead", "gid").where("a <> b").distinct()
    star = materialize(star, "shingle-star")
    links = verified(rows, star, nodes, width, share)
    labels = connected_components(links)
    # What is left: pairs of groups that meet over a token and don't lie in one component yet.
    placed = nodes.join(labels, F.col("sig") == F.col("node"), "left").select("sig", "gid", "parity", F.coalesce("root", "sig").alias("root"))
    placed = materialize(placed, "shingle-placed")
    spread = placed.groupBy("gid").agg(F.min("root").alias("low"), F.max("root").alias("high"), F.when(F.count("*") == 1, F.first("parity")).alias("whole"))
    other = lambda df, *more: df.select(F.col("token").alias("t"), F.col("gid").alias("g2"), F.col("n").alias("n_2"), F.col("pos").alias("pos_2"), F.col("bits").alias("bits_2"), *more)
    # Of a hub group of several nodes only the first has met the others, so such a hub meets them here too.
    few = meeting.where(F.col("c") <= MANY).join(own.select(F.col("gid").alias("several")), (F.col("gid") == F.col("several")) & (F.col("gid") == F.col("hub")), "left")
    few = few.where((F.col("gid") != F.col("hub")) | F.col("several").isNotNull())
    plain = few.join(other(few), (F.col("token") == F.col("t")) & (F.col("gid") < F.col("g2")) & compatible("", "_2", share)).select(F.col("gid").alias("g1"), "g2").distinct()
    span = lambda k: spread.select(F.col("gid").alias(f"s{k}"), F.col("low").alias(f"low{k}"), F.col("high").alias(f"high{k}"))
    whole_in_one = (F.col("low1") == F.col("high1")) & (F.col("low2") == F.col("high2")) & (F.col("low1") == F.col("low2"))
    plain = plain.join(span(1), F.col("g1") == F.col("s1")).join(span(2), F.col("g2") == F.col("s2")).where(~whole_in_one).select("g1", "g2")
    # Over a token of many groups only those outside their hub's component go on, and meet the rest.
    hub_root = spread.select(F.col("gid").alias("hg"), F.col("low").alias("hub_low"), F.col("high").alias("hub_high"))
    tagged = meeting.where(F.col("c") > MANY).join(spread.withColumnRenamed("gid", "g"), F.col("gid") == F.col("g")).join(hub_root, F.col("hub") == F.col("hg"))
    settled = (F.col("low") == F.col("high")) & (F.col("hub_low") == F.col("hub_high")) & (F.col("low") == F.col("hub_low"))
    tagged = materialize(tagged.select("token", "gid", "n", "pos", "bits", "whole", "low", "high", (~settled).alias("open")), "shingle-open")
    others = other(tagged, F.col("whole").alias("whole_2"), F.col("low").alias("low2"), F.col("high").alias("high2"), F.col("open").alias("open2"))
    apart = ~((F.col("low") == F.col("high")) & (F.col("low2") == F.col("high2")) & (F.col("low") == F.col("low2")))
    differ = sum((F.bit_count(F.col("whole")[k].bitwiseXOR(F.col("whole_2")[k])) for k in range(1, PARITY_WORDS)), F.bit_count(F.col("whole")[0].bitwiseXOR(F.col("whole_2")[0])))
    whole = differ * (100 + share) <= (100 - share) * (F.col("n") + F.col("n_2"))
    crowded = tagged.where("open").join(others, (F.col("token") == F.col("t")) & ((F.col("gid") < F.col("g2")) | ((F.col("gid") > F.col("g2")) & ~F.col("open2"))) & apart & compatible("", "_2", share) & F.coalesce(whole, F.lit(True))).select(F.col("gid").alias("g1"), "g2")
    rest = plain.unionByName(crowded).distinct()
    mixed = spread.where("low <> high").select(F.col("gid").alias("g1"), F.col("gid").alias("g2"))
    first = placed.select(F.col("gid").alias("x"), F.col("sig").alias("a"), F.col("root").alias("ra"))
    second = placed.select(F.col("gid").alias("y"), F.col("sig").alias("b"), F.col("root").alias("rb"))
    left = rest.unionByName(mixed).join(first, F.col("g1") == F.col("x")).join(second, F.col("g2") == F.col("y")).where("ra <> rb").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    done = star.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    again = materialize(left.join(done, ["a", "b"], "left_anti"), "shingle-again")
    discard(meeting, star, placed, tagged, lead)
    more = verified(rows, again, nodes, width, share)
    roots = connected_components(links.unionByName(more))
    discard(again, links, more, nodes)
    return labelled(found, roots)


def labelled(found: DataFrame, roots: DataFrame) -> DataFrame:
    """Every row with its component; ids are reduced per set and then per component before they are joined back."""
    sets = found.where("n > 0").groupBy("sig").agg(F.min("doc_id").alias("least"), F.count("*").alias("rows"))
    rooted = sets.join(roots, F.col("sig") == F.col("node"), "left").select("sig", "least", "rows", F.coalesce("root", "sig").alias("root"))
    whole = rooted.groupBy("root").agg(F.min("least").alias("component_id"), F.sum("rows").alias("n_linked")).withColumnRenamed("root", "r")
    known = rooted.join(whole, F.col("root") == F.col("r")).select(F.col("sig").alias("s"), "component_id", "n_linked", "root")
    own = F.col("sig").isNull()
    return found.join(known, F.col("sig") == F.col("s"), "left").select("doc_id", "tkey", F.col("n").alias("n_shingles"), F.when(own, F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id"), F.when(own, F.lit(1)).otherwise(F.col("n_linked")).cast("long").alias("n_linked"), "root")


def keep_one_of_each(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", width: int = 5, share: int = 80) -> DataFrame:
    """docs with one row of each component, all columns kept: the row with the smallest id (nulls last) and text key.

    Documents without words are in no component and stay. Rows that repeat both id and text count as one."""
    found = near_components(docs, id_col=id_col, text_col=text_col, width=width, share=share)
    place = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "tkey")
    best = found.where("n_shingles > 0").groupBy("root").agg(F.min(place).alias("best"))
    kept = best.select("best.doc_id", "best.tkey").unionByName(found.where("n_shingles = 0").select("doc_id", "tkey").distinct())
    own = F.struct(named(docs, id_col).alias("doc_id"), text_key(named(docs, text_col)).alias("tkey"))
    held = docs.select(F.struct(*(named(docs, c) for c in docs.columns)).alias("row"), own.alias("own"))
    wanted = kept.select(F.struct("doc_id", "tkey").alias("of"))
    # A struct of nulls equals another, so plain equality will do, and rows stay where the join has put them.
    once = held.join(wanted, held["own"] == wanted["of"], "left_semi").groupBy("own").agg(F.first("row").alias("row"))
    return once.select("row.*")
