"""Language-model scoring by context-tree weighting over bytes.

Every byte is eight binary decisions. For each decision (the bits of the byte so far) there is a tree of contexts, the
preceding 0 to DEPTH bytes; every node keeps Krichevsky-Trofimov counts, and the weighted probability of a node mixes
its own estimate with the product of its children's, half and half, bottom up. The frozen tree gives each byte the
mixture of the estimates on its context path.

How it is spread: texts are gathered in blocks. A block's distinct (context, byte) grams and distinct tokens are looked up once a
block, not once a position. They are dealt by hash of the nearest context bytes into buckets, which hold
whole subtrees, so that each bucket builds its part of the tree alone and answers the blocks' grams. No table of the
model is broadcast but the nodes of depth 0 to 2, of which there are at most 255 * (1 + 256 + 256^2)."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
import zlib
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize, mix64, pick, segments, slices, utf8_buffer, word_stream

#: Context bytes. A gram is the context, nearest byte first, and then the byte itself: 48 bits.
DEPTH = 5
#: Depth of the nodes at which a bucket's subtrees hang; shallower nodes are shared.
SHARED = 3
#: Bytes of text in a block, and positions handled at once within it.
BLOCK, SPAN = 16 << 20, 1 << 20
GRAM_BITS = 8 * (DEPTH + 1)


# -- numbers


def log_gamma(x: np.ndarray) -> np.ndarray:
    """ln Gamma for x > 0: shifted up by 8, then Stirling's series."""
    shift, y = np.zeros_like(x), x.astype(float)
    for k in range(8):
        shift += np.log(y + k)
    y = y + 8
    z = 1 / (y * y)
    series = (1 / 12 - z * (1 / 360 - z * (1 / 1260 - z / 1680))) / y
    return (y - 0.5) * np.log(y) - y + 0.5 * math.log(2 * math.pi) + series - shift


def log_kt(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """ln of the Krichevsky-Trofimov probability of a sequence with a zeros and b ones."""
    a, b = a.astype(float), b.astype(float)
    return log_gamma(a + 0.5) + log_gamma(b + 0.5) - log_gamma(a + b + 1) - math.log(math.pi)


# -- grams of a block


def grams(stream: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The gram at every position of a word stream, as int64, and the number of its text.

    Contexts before a text's start are filled with 0x0A, so texts don't see each other."""
    ends = stream == 0x0A
    repeat = np.where(ends, DEPTH, 1)
    padded = np.concatenate([np.full(DEPTH, 0x0A, np.uint8), np.repeat(stream, repeat)]).astype(np.int64)
    at = np.cumsum(repeat) - repeat + DEPTH
    code = np.zeros(len(stream), np.int64)
    for back in range(1, DEPTH + 1):
        code = (code << 8) | padded[at - back]
    return (code << 8) | padded[at], np.cumsum(ends) - ends


def spans(stream: np.ndarray) -> Iterator[tuple[int, int]]:
    """Cuts between texts, about SPAN positions apart (a longer text stands alone)."""
    ends = np.flatnonzero(stream == 0x0A) + 1
    start = 0
    while start < len(stream):
        k = np.searchsorted(ends, start + SPAN, side="right") - 1
        stop = int(ends[k]) if k >= 0 and ends[k] > start else int(ends[np.searchsorted(ends, start, side="right")])
        yield start, stop
        start = stop


def merged(keys: list[np.ndarray], counts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    if not keys:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    found, at = np.unique(np.concatenate(keys), return_inverse=True)
    return found, np.bincount(at, weights=np.concatenate(counts), minlength=len(found)).astype(np.int64)


def block_grams(stream: np.ndarray, learn: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct grams of a block and how often each occurs in texts to learn from."""
    keys, counts, first = [], [], 0
    for start, stop in spans(stream):
        code, doc = grams(stream[start:stop])
        at, found = pd.factorize(code)
        keys.append(found)
        counts.append(np.bincount(at, weights=learn[first + doc], minlength=len(found)))
        first += int(doc[-1]) + 1
        if len(keys) == 4:
            k, c = merged(keys, counts)
            keys, counts = [k], [c]
    return merged(keys, counts)


def block_tokens(stream: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct tokens of a block as 64-bit hashes, the index of each token, and the ends among the tokens."""
    array, ends = segments(stream)
    coded = pc.dictionary_encode(array)
    hashes = np.fromiter((xxhash.xxh3_64_intdigest(t) for t in coded.dictionary.to_pylist()), np.uint64, len(coded.dictionary)).view(np.int64)
    keys, to = np.unique(hashes, return_inverse=True)
    return keys, to[np.asarray(coded.indices)], ends


def bucket_of(keys: np.ndarray, is_gram: bool, buckets: int) -> np.ndarray:
    """Grams go by their SHARED nearest context bytes, tokens by themselves."""
    own = keys >> (8 * (DEPTH + 1 - SHARED)) if is_gram else keys
    return (mix64(own) % np.uint64(buckets)).astype(np.int64)


def packed(values: np.ndarray) -> bytes:
    return zstandard.compress(np.ascontiguousarray(values).tobytes(), 1)


def packed_sorted(values: np.ndarray) -> bytes:
    """Ascending integers by their differences, byte plane by byte plane."""
    return packed(np.diff(values, prepend=np.int64(0)).astype("<i8").view(np.uint8).reshape(-1, 8).T)


def unpacked(data: bytes, kind: str) -> np.ndarray:
    return np.frombuffer(zstandard.decompress(data), kind)


def unpacked_sorted(data: bytes) -> np.ndarray:
    planes = unpacked(data, np.uint8).reshape(8, -1)
    return np.cumsum(np.ascontiguousarray(planes.T).view("<i8").reshape(-1))


# -- the tree of a bucket


def levels_of(codes: np.ndarray, counts: np.ndarray, top: int) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """For each depth, sorted distinct (context, byte) keys and counts; codes sorted."""
    out = {}
    for depth in range(top, DEPTH + 1):
        key = ((codes >> (8 * (DEPTH + 1 - depth))) << 8) | (codes & 0xFF)
        found, at = np.unique(key, return_inverse=True)
        out[depth] = (found, np.bincount(at, weights=counts, minlength=len(found)))
    return out


def bit_nodes(keys: np.ndarray, counts: np.ndarray, bit: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Nodes that decide bit `bit` (0: the highest): keys context << 8 | (1 and the bits so far), zeros, ones."""
    symbol = keys & 0xFF
    node = (keys >> 8 << 8) | (1 << bit) | (symbol >> (8 - bit))
    first = np.flatnonzero(np.diff(node, prepend=-1))
    one = (symbol >> (7 - bit)) & 1
    total = np.add.reduceat(counts, first) if len(first) else np.zeros(0)
    ones = np.add.reduceat(counts * one, first) if len(first) else np.zeros(0)
    return node[first], total - ones, ones


def weigh(nodes: dict[int, tuple], top: int, below: dict | None = None) -> dict[int, tuple]:
    """Per depth (key, zeros, ones, share, ln weighted): share is the weight of the node's own estimate, bottom up."""
    out: dict[int, tuple] = {}
    for depth in sorted(nodes, reverse=True):
        key, a, b = nodes[depth]
        own = log_kt(a, b)
        if depth == DEPTH:
            out[depth] = (key, a, b, np.ones(len(key)), own)
            continue
        if depth + 1 in out:
            child_key, _, _, _, child = out[depth + 1]
            parent = (child_key >> 16 << 8) | (child_key & 0xFF)
            at = np.searchsorted(key, parent)
            product = np.bincount(at, weights=child, minlength=len(key))
        else:
            product = below[depth]
        share = 1 / (1 + np.exp(np.clip(product - own, -700, 700)))
        out[depth] = (key, a, b, share, np.logaddexp(own, product) + math.log(0.5))
    return out


def find(keys: np.ndarray, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    if not len(keys):
        return np.zeros(len(wanted), np.int64), np.zeros(len(wanted), bool)
    at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
    return at, keys[at] == wanted


def log_probability(codes: np.ndarray, trees: list[dict[int, tuple]]) -> np.ndarray:
    """log10 of the mixture for each gram; trees[bit] holds the weighed nodes of all depths from 0."""
    total = np.zeros(len(codes))
    symbol = codes & 0xFF
    for bit in range(8):
        prefix, one = (1 << bit) | (symbol >> (8 - bit)), (symbol >> (7 - bit)) & 1
        p = np.full(len(codes), 0.5)
        for depth in range(DEPTH, -1, -1):
            key, a, b, share, _ = trees[bit][depth]
            at, there = find(key, (codes >> (8 * (DEPTH + 1 - depth)) << 8) | prefix)
            if not there.any():
                continue
            at = at[there]
            own = (np.where(one[there] == 1, b[at], a[at]) + 0.5) / (a[at] + b[at] + 1)
            p[there] = share[at] * own + (1 - share[at]) * p[there]
        total += np.log10(p)
    return total


def bucket_trees(codes: np.ndarray, counts: np.ndarray) -> list[dict[int, tuple]]:
    levels = levels_of(codes, counts, SHARED)
    return [weigh({d: bit_nodes(*levels[d], bit) for d in levels}, SHARED) for bit in range(8)]


def shared_trees(frame: pd.DataFrame) -> list[dict[int, tuple]]:
    """The nodes of depth 0 to SHARED - 1, from the buckets' sums for depth SHARED - 1: key, zeros, ones, product."""
    trees = []
    for bit in range(8):
        part = frame[frame["bit"] == bit].sort_values("node")
        key, a, b, product = (part[c].to_numpy() for c in ("node", "zeros", "ones", "product"))
        nodes = {SHARED - 1: (key, a.astype(float), b.astype(float))}
        for depth in range(SHARED - 2, -1, -1):
            k, x, y = nodes[depth + 1]
            found, at = np.unique((k >> 16 << 8) | (k & 0xFF), return_inverse=True)
            nodes[depth] = (found, np.bincount(at, weights=x, minlength=len(found)), np.bincount(at, weights=y, minlength=len(found)))
        trees.append(weigh(nodes, 0, {SHARED - 1: product.astype(float)}))
    return trees


# -- Spark


def held_out(ids: pa.Array, modulus: int = 7, rest: int = 2) -> np.ndarray:
    """crc32 of the id as text (null: empty text) leaves `rest`."""
    return np.array([zlib.crc32(b"" if i is None else str(i).encode()) % modulus == rest for i in ids.to_pylist()], bool)


def cut_blocks(docs: DataFrame, buckets: int) -> DataFrame:
    """(block, bucket, text, keys, counts, tokens, token_counts): bucket -1 holds a block's texts and ids, the others
    its distinct grams and tokens of that bucket with their counts in texts to learn from."""

    def emit(block: str, ids: list[pa.Array], held: np.ndarray, stream: np.ndarray) -> Iterator[pa.RecordBatch]:
        learn = (~held).astype(float)
        id_table = pa.concat_arrays(ids)
        sink = pa.BufferOutputStream()
        with pa.ipc.new_stream(sink, pa.schema([("doc_id", id_table.type)])) as writer:
            writer.write_batch(pa.RecordBatch.from_arrays([id_table], names=["doc_id"]))
        rows = [(block, -1, zstandard.compress(stream.tobytes(), 1), sink.getvalue().to_pybytes(), packed(held), None, None)]
        keys, counts = block_grams(stream, learn)
        tokens, at, ends = block_tokens(stream)
        doc = np.cumsum(ends) - ends
        times = np.bincount(at, weights=learn[doc], minlength=len(tokens)).astype(np.int64)
        gram_bucket, token_bucket = bucket_of(keys, True, buckets), bucket_of(tokens, False, buckets)
        by_gram, by_token = np.argsort(gram_bucket, kind="stable"), np.argsort(token_bucket, kind="stable")
        gram_cut = np.searchsorted(gram_bucket[by_gram], np.arange(buckets + 1))
        token_cut = np.searchsorted(token_bucket[by_token], np.arange(buckets + 1))
        for k in range(buckets):
            g, t = by_gram[gram_cut[k] : gram_cut[k + 1]], by_token[token_cut[k] : token_cut[k + 1]]
            if len(g) or len(t):
                rows.append((block, k, None, packed_sorted(keys[g]), packed(counts[g].astype("<u4")), packed_sorted(tokens[t]), packed(times[t].astype("<u4"))))
        for i in range(0, len(rows), 64):
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows[i : i + 64], strict=True), BLOCK_TYPES, strict=True)], names=list(BLOCK_COLUMNS))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        task, serial = TaskContext.get().partitionId(), 0
        ids, held, streams, size = [], [], [], 0
        for batch in slices(batches, "text", BLOCK // 4):
            stream = word_stream(*utf8_buffer(batch.column(1)), lower=True)
            if size and size + len(stream) > BLOCK:
                yield from emit(f"{task}-{serial}", ids, np.concatenate(held), np.concatenate(streams))
                ids, held, streams, size, serial = [], [], [], 0, serial + 1
            ids.append(batch.column(0))
            held.append(held_out(batch.column(0)))
            streams.append(stream)
            size += len(stream)
        if size:
            yield from emit(f"{task}-{serial}", ids, np.concatenate(held), np.concatenate(streams))

    return docs.mapInArrow(run, "block string, bucket int, text binary, keys binary, counts binary, tokens binary, token_counts binary")


BLOCK_COLUMNS = ("block", "bucket", "text", "keys", "counts", "tokens", "token_counts")
BLOCK_TYPES = (pa.string(), pa.int32(), pa.binary(), pa.binary(), pa.binary(), pa.binary(), pa.binary())


def gathered(table: pa.Table) -> tuple[list, list, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """A bucket's rows unpacked: per row its grams and tokens; all together the sorted distinct ones with counts."""
    own_grams = [unpacked_sorted(x.as_py()) for x in table["keys"]]
    own_tokens = [unpacked_sorted(x.as_py()) for x in table["tokens"]]
    codes, counts = merged(own_grams, [unpacked(x.as_py(), "<u4") for x in table["counts"]])
    tokens, times = merged(own_tokens, [unpacked(x.as_py(), "<u4") for x in table["token_counts"]])
    return own_grams, own_tokens, codes, counts, tokens, times


def shared_sums(parts: DataFrame) -> DataFrame:
    """What each bucket adds to the nodes of depth SHARED - 1; bit -1: tokens in all (zeros) and distinct (ones)."""

    def run(table: pa.Table) -> pa.Table:
        _, _, codes, counts, tokens, times = gathered(table)
        bits, nodes, zeros, ones, products = [np.array([-1])], [np.array([0])], [np.array([float(times.sum())])], [np.array([float((times > 0).sum())])], [np.zeros(1)]
        known = counts > 0
        for bit, tree in enumerate(bucket_trees(codes[known], counts[known])):
            key, a, b, _, weighted = tree[SHARED]
            found, at = np.unique((key >> 16 << 8) | (key & 0xFF), return_inverse=True)
            bits.append(np.full(len(found), bit))
            nodes.append(found)
            for into, values in ((zeros, a), (ones, b), (products, weighted)):
                into.append(np.bincount(at, weights=values, minlength=len(found)))
        return pa.table({"bit": pa.array(np.concatenate(bits), pa.int32()), "node": pa.array(np.concatenate(nodes), pa.int64()), "zeros": np.concatenate(zeros), "ones": np.concatenate(ones), "product": np.concatenate(products)})

    local = parts.groupBy("bucket").applyInArrow(run, "bit int, node long, zeros double, ones double, product double")
    return local.groupBy("bit", "node").agg(F.sum("zeros").alias("zeros"), F.sum("ones").alias("ones"), F.sum("product").alias("product"))


def answers(parts: DataFrame, shared) -> DataFrame:
    """(block, bucket, scores, token_counts): for a block's grams and tokens of a bucket, in their sorted order, the
    log10 probabilities and the counts in training texts."""

    def run(table: pa.Table) -> pa.Table:
        own_grams, own_tokens, codes, counts, tokens, times = gathered(table)
        known = counts > 0
        deep = bucket_trees(codes[known], counts[known])
        trees = [deep[bit] | {d: shared.value[bit][d] for d in range(SHARED)} for bit in range(8)]
        scores = log_probability(codes, trees)
        return pa.table({"block": table["block"], "bucket": table["bucket"], "scores": pa.array([packed(scores[np.searchsorted(codes, g)].astype("<f4")) for g in own_grams], pa.binary()), "found": pa.array([packed(times[np.searchsorted(tokens, t)].astype("<i8")) for t in own_tokens], pa.binary())})

    return parts.groupBy("bucket").applyInArrow(run, "block string, bucket int, scores binary, found binary")


def block_scores(texts: DataFrame, answered: DataFrame, buckets: int, n_train: float, n_types: float, id_type: str) -> DataFrame:
    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        stream = np.frombuffer(zstandard.decompress(left["text"][0].as_py()), np.uint8)
        ids = pa.ipc.open_stream(left["keys"][0].as_py()).read_all()["doc_id"].combine_chunks()
        held = unpacked(left["counts"][0].as_py(), bool)
        keys, _ = block_grams(stream, np.zeros(len(held)))
        tokens, at, ends = block_tokens(stream)
        scores, found = np.zeros(len(keys)), np.zeros(len(tokens), np.int64)
        gram_bucket, token_bucket = bucket_of(keys, True, buckets), bucket_of(tokens, False, buckets)
        by_gram, by_token = np.argsort(gram_bucket, kind="stable"), np.argsort(token_bucket, kind="stable")
        gram_cut = np.searchsorted(gram_bucket[by_gram], np.arange(buckets + 1))
        token_cut = np.searchsorted(token_bucket[by_token], np.arange(buckets + 1))
        for bucket, packed_scores, packed_found in zip(right["bucket"].to_pylist(), right["scores"].to_pylist(), right["found"].to_pylist(), strict=True):
            scores[by_gram[gram_cut[bucket] : gram_cut[bucket + 1]]] = unpacked(packed_scores, "<f4")
            found[by_token[token_cut[bucket] : token_cut[bucket + 1]]] = unpacked(packed_found, "<i8")
        n, total, first = len(held), np.zeros(len(held)), 0
        for start, stop in spans(stream):
            code, doc = grams(stream[start:stop])
            at_span, distinct = pd.factorize(code)
            value = scores[np.searchsorted(keys, distinct)][at_span]
            sums = np.bincount(doc, weights=value)
            total[first : first + len(sums)] += sums
            first += len(sums)
        doc = np.cumsum(ends) - ends
        base = np.bincount(doc, weights=np.log10((found + 1) / (n_train + n_types + 1))[at], minlength=n)
        return pa.table({"doc_id": ids, "held_out": held, "n_tokens": np.bincount(doc, minlength=n).astype(np.int64), "n_known": np.bincount(doc, weights=(found > 0)[at], minlength=n).astype(np.int64), "train_tokens": np.full(n, int(n_train), np.int64), "base_score": base, "score": total, "n_bytes": np.diff(np.flatnonzero(stream == 0x0A), prepend=-1).astype(np.int64)})

    names = f"doc_id {id_type}, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double, n_bytes long"
    return texts.groupBy("block").cogroup(answered.groupBy("block")).applyInArrow(run, names)


def score_documents(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs -> (doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, n_bytes, bits_per_byte).

    Texts have A-Z lower-cased and are scored as their words, each with the white space after it as one space, and one
    end; score is log10 of the model's probability of that sequence of n_bytes bytes, bits_per_byte its code length.
    Null texts and texts without words are a lone end. Learned from the rows whose crc32(id as text) mod 7 is not 2 (a
    null id counts as the empty text); every row is scored, repeated rows each. An empty table gives no rows. Token
    counts are kept under 64-bit hashes of the tokens."""
    chosen = pick(docs, doc_id=id_col, text=text_col)
    size = chosen.agg(F.sum(F.octet_length("text"))).collect()[0][0] or 0
    buckets = max(8, math.ceil(size / (2 * BLOCK)))
    blocks = materialize(cut_blocks(chosen, buckets), "ctw-blocks")
    parts = blocks.where("bucket >= 0").select("block", "bucket", "keys", "counts", "tokens", "token_counts")
    sums = shared_sums(parts).toPandas()  # at most 255 * 256^2 rows, whatever the corpus
    tokens = sums[sums["bit"] < 0]
    n_train, n_types = float(tokens["zeros"].sum()), float(tokens["ones"].sum())
    shared = docs.sparkSession.sparkContext.broadcast(shared_trees(sums))
    texts = blocks.where("bucket = -1").select("block", "text", "keys", "counts")
    scored = block_scores(texts, answers(parts, shared), buckets, n_train, n_types, chosen.schema["doc_id"].dataType.simpleString())
    return scored.withColumn("bits_per_byte", -F.col("score") * F.lit(math.log2(10)) / F.col("n_bytes"))
