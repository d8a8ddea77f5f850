"""Each operator against brute force on small tables with every awkward case, and against SQL where there is some."""

import hashlib
import itertools
import json
import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from tests.compare import database, same
from waysite.llm import bpe, context_tree, graph, line_dedup, mixing, quality, queries, shingle_join, telephony, tokencount, toxicity, warc
from waysite.llm.common import utf8_buffer, word_stream

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size string, target string, taken string, score string, sig string"


def lower(t):
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in t)


def rows():
    rng = random.Random(5)
    vocabulary = ["alpha", "beta", "Gamma", "delta,", "été", "日本", "the", "of", "a", "don't", "x" * 300]
    base = [" ".join(rng.choice(vocabulary) for _ in range(rng.randrange(5, 80))) for _ in range(30)]
    texts = [*base, *base[:6], base[0] + " extra", base[1].upper(), None, "", "   \t\n ", "one", "two words", "\n".join(base[:3]) + "\n" + base[2], "é" * 5000, "<|endoftext|> hi\x0bthere\r\n", " ".join(base * 20)]
    out = [(i, t, rng.choice(["en", "de", None]), rng.choice(["s1", "s2", "s1", None]), 0, *"abcde") for i, t in enumerate(texts)]
    return [*out, out[3], out[3], (None, "null id text here", "en", "s1", 0, *"abcde"), (None, None, None, None, None, *"abcde")]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(rows(), SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def con(sf_dir):
    return database(sf_dir)


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_equals_sql(spark, sf_dir, con, name):
    same(queries.QUERIES[name](spark, sf_dir), con, queries.ORACLES[name])


def test_empty_tables(spark, empty):
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    pages = spark.createDataFrame([], "page_id long, url string, html string")
    model = toxicity.train(empty, labels)
    path = public_tokenizers.path
    for df in (context_tree.score_documents(empty), mixing.mix_sources(empty), mixing.mix_rows(empty), line_dedup.removed_lines(empty), line_dedup.drop_lines(empty), telephony.stored_digests(empty), bpe.encode_documents(empty, path("word_bpe_49k.json")), shingle_join.near_components(empty), shingle_join.keep_one_of_each(empty), tokencount.count_tokens(empty, path("piece_bpe_32k.model")), toxicity.score_documents(empty, model), warc.crawl_round_trip(pages), quality.judge(empty), quality.keep_good(empty)):
        assert df.count() == 0


# -- 1


def test_context_tree_matches_a_plain_mixture(spark):
    """The same numbers from a dictionary of contexts, weighed bottom up in exact arithmetic order."""
    texts = {0: "abab abba ab", 1: "abba abab", 2: "AB ba  ab", 3: "", 4: "zebra ab", 5: None, 12: "ab ab"}
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    got = {r["doc_id"]: r for r in context_tree.score_documents(df).collect()}
    depth = context_tree.DEPTH

    def stream(t):
        return ("".join(w + " " for w in WORD.findall(lower(t or ""))) + "\n").encode()

    held = {i: zlib.crc32(str(i).encode()) % 7 == 2 for i in texts}
    counts = Counter()
    for i, t in texts.items():
        if not held[i]:
            s = b"\n" * depth + stream(t)
            for p in range(depth, len(s)):
                for d in range(depth + 1):
                    context = s[p - d : p][::-1]
                    for bit in range(8):
                        counts[context, (1 << bit) | (s[p] >> (8 - bit)), (s[p] >> (7 - bit)) & 1] += 1
    nodes = {(c, x) for c, x, _ in counts}
    kt = lambda a, b: math.lgamma(a + 0.5) + math.lgamma(b + 0.5) - math.lgamma(a + b + 1) - math.log(math.pi)
    children = {}
    for c, x in nodes:
        if c:
            children.setdefault((c[:-1], x), []).append((c, x))
    weighted, share = {}, {}
    for c, x in sorted(nodes, key=lambda n: -len(n[0])):
        own = kt(counts[c, x, 0], counts[c, x, 1])
        if len(c) == depth:
            weighted[c, x] = own
            continue
        product = sum(weighted[n] for n in children[c, x])
        weighted[c, x] = np.logaddexp(own, product) + math.log(0.5)
        share[c, x] = math.exp(math.log(0.5) + own - weighted[c, x])
    for i, t in texts.items():
        s, total = b"\n" * depth + stream(t), 0.0
        for q in range(depth, len(s)):
            for bit in range(8):
                x, one = (1 << bit) | (s[q] >> (8 - bit)), (s[q] >> (7 - bit)) & 1
                p = 0.5
                for d in range(depth, -1, -1):
                    c = s[q - d : q][::-1]
                    if (c, x) in nodes:
                        a, b = counts[c, x, 0], counts[c, x, 1]
                        own = ((b if one else a) + 0.5) / (a + b + 1)
                        p = own if d == depth else share[c, x] * own + (1 - share[c, x]) * p
                total += math.log10(p)
        assert got[i]["score"] == pytest.approx(total, rel=1e-5), i
        assert got[i]["held_out"] == held[i]
    tokens = {i: [*WORD.findall(lower(t or "")), "\n"] for i, t in texts.items()}
    known = Counter(w for i in texts if not held[i] for w in tokens[i])
    n, v = sum(known.values()), len(known)
    for i in texts:
        assert (got[i]["n_tokens"], got[i]["n_known"], got[i]["train_tokens"]) == (len(tokens[i]), sum(known[w] > 0 for w in tokens[i]), n)
        assert got[i]["base_score"] == pytest.approx(sum(math.log10((known[w] + 1) / (n + v + 1)) for w in tokens[i]), rel=1e-9)


def test_context_tree_beats_single_words(spark, sf_dir):
    p = queries.op1_context_tree(spark, sf_dir.replace("0.001", "0.1")).toPandas()
    out = p[p["held_out"]]
    assert len(p) == 10_000 and len(out) and out["score"].sum() > out["base_score"].sum()


def test_context_tree_odd_rows(docs):
    found = context_tree.score_documents(docs).collect()
    assert len(found) == len(rows()) and all(r["score"] < 0 for r in found)


# -- 2


def test_mixing(spark, docs):
    found = mixing.mix_sources(docs).collect()
    assert len(found) == len(rows())
    again = mixing.mix_sources(docs.repartition(5)).collect()
    key = lambda r: (r["doc_id"] is None, r["doc_id"], r["size"], r["copies"])
    assert sorted(map(key, found), key=str) == sorted(map(key, again), key=str)
    assert all(0 <= r["copies"] <= 3 and r["taken"] == r["copies"] * r["size"] for r in found)
    assert {r["source"] for r in found} == {None, "s1", "s2"}
    mixed = mixing.mix_rows(docs).collect()
    assert sum(len(WORD.findall(r["text"] or "")) for r in mixed) == sum(r["taken"] for r in found)
    assert mixing.mix_rows(docs).columns == docs.columns


def test_mixing_targets(spark):
    sizes = {"a": 1000, "b": 10, "c": 500, None: 90}
    df = spark.createDataFrame([(s, v, 1) for s, v in sizes.items()], "source string, source_size long, n_docs long")
    got = {r["source"]: r["target"] for r in mixing.size_targets(df).collect()}
    # By hand: weights 5, 2, 1, 5 over 1600 words; b stops at 30 and the null source at 270; a and c share the rest 5 : 1.
    assert got == pytest.approx({"b": 30.0, None: 270.0, "a": 1300 * 5 / 6, "c": 1300 / 6})


def test_mixing_comes_near_its_targets(spark, sf_dir):
    p = mixing.mix_sources(spark.read.parquet(f"{sf_dir.replace('0.001', '0.01')}/documents.parquet")).toPandas()
    for _, g in p.groupby("source"):
        assert abs(g["taken"].sum() - g["target"].iloc[0]) <= max(g["size"].max(), 0.05 * g["target"].iloc[0])


# -- 3


def brute_lines(data, share=80, least=line_dedup.LEAST_WORDS):
    lines = []
    for doc_id, text, *_ in sorted({r[:2] for r in data}, key=lambda r: (r[0] is not None, r[0] or 0, r[1] or "")):
        for k, line in enumerate((text or "").split("\n")):
            lines.append(((doc_id, text), k, frozenset(w.lower() for w in WORD.findall(line))))
    gone = {}
    for i, (doc, k, words) in enumerate(lines):
        gone.setdefault(doc, [])
        if len(words) >= least and any(len(o) >= least and 100 * len(words & o) >= share * len(words | o) for _, _, o in lines[:i]):
            gone[doc].append(k)
    return gone


def test_line_dedup(spark):
    rng = random.Random(9)
    words = [f"w{k}" for k in range(40)]
    lines = [" ".join(rng.sample(words, rng.randrange(3, 30))) for _ in range(40)]
    lines += [" ".join([*x.split()[:-1], "changed"]) for x in lines[:15]] + [x.upper() for x in lines[:3]] + ["", "\t \x0b", "short line"] + [" ".join(rng.sample([f"v{k}" for k in range(400)], 200))] * 2
    data = [(i, "\n".join(rng.sample(lines, 6))) for i in range(25)] + [(99, None), (100, ""), (None, lines[0])]
    df = spark.createDataFrame([*data, data[0]], "doc_id long, text string")
    keys = {(r["doc_id"], r["tkey"]): r["removed"] for r in line_dedup.removed_lines(df).collect()}
    want = brute_lines(data)
    assert len(keys) == len(want)
    assert sorted((str(d), g) for (d, _), g in keys.items()) == sorted((str(d), g) for (d, _), g in want.items())
    kept = {r["doc_id"]: r["text"] for r in line_dedup.drop_lines(df).collect()}
    for (doc, text), gone in want.items():
        left = "\n".join(x for k, x in enumerate((text or "").split("\n")) if k not in gone) if text is not None else None
        assert (kept[doc] == left) if not gone or WORD.search(left) else doc not in kept


def test_line_dedup_crowded_words(spark, monkeypatch):
    """The way by hubs, for words that very many lines hold, gives the same."""
    monkeypatch.setattr(line_dedup, "MANY", 2)
    rng = random.Random(4)
    data = [(i, " ".join(["rare1", "rare2", *rng.sample([f"c{k}" for k in range(14)], 9)])) for i in range(60)]
    df = spark.createDataFrame(data, "doc_id long, text string")
    got = {r["doc_id"]: r["removed"] for r in line_dedup.removed_lines(df).collect()}
    assert got == {d: g for (d, _), g in brute_lines(data).items()}


# -- 4


def test_telephony(docs):
    for codec in (telephony.MU_LAW, telephony.A_LAW, telephony.ADPCM, None):
        media = telephony.store_media(docs, codec=codec)
        stored = {(r["doc_id"], r["n_bytes"]): bytes(r["media"]) for r in media.collect()}
        found = telephony.stored_digests(docs, codec=codec).collect()
        assert len(found) == len(rows())
        texts = Counter((i, t or "") for i, t, *_ in rows())
        for (i, t), n in texts.items():
            raw = t.encode()
            payload = raw + bytes(-len(raw) % 64 or (0 if raw else 64))
            mine = [r for r in found if r["doc_id"] == i and r["n_bytes"] == len(raw) and r["payload_sha256"] == hashlib.sha256(payload).hexdigest()]
            assert len(mine) == n
            r, file = mine[0], stored[i, len(raw)]
            assert (r["payload_bytes"], r["tail_crc32"], r["media_bytes"], r["media_sha256"]) == (len(payload), zlib.crc32(payload[-64:]), len(file), hashlib.sha256(file).hexdigest())
            kind, rate, data = telephony.read_wav(file)
            assert rate == 8000 and kind == (codec or (telephony.MU_LAW, telephony.A_LAW, telephony.ADPCM)[zlib.crc32(payload) % 3])
            pcm = telephony.expand(kind, np.frombuffer(data, np.uint8)).astype(int).tolist()
            low = [sum(pcm[k : k + 2]) // len(pcm[k : k + 2]) for k in range(0, len(pcm), 2)]
            crossings = sum((x < 0) != (y < 0) for x, y in zip(low, low[1:]))
            assert r["feature"] == f"{kind}@4000:{len(low)}:{max(map(abs, low))}:{sum(map(abs, low)) // len(low)}:{crossings}:{zlib.crc32(np.array(low, '<i2').tobytes()):08x}"


def test_resample():
    x = np.array([0, 10, -30, 7], np.int16)
    assert telephony.resample(x, 2, 1).tolist() == [0, 5, 10, -10, -30, -12, 7, 7]
    assert telephony.resample(x, 1, 2).tolist() == [5, -12] and telephony.resample(x, 1, 3).tolist() == [-7, 7]
    assert telephony.resample(np.zeros(0, np.int16), 1, 2).tolist() == []


def test_codecs():
    assert telephony.MU_LAW_PCM[[0x00, 0x80, 0xFF, 0x7F]].tolist() == [-32124, 32124, 0, 0]
    assert telephony.A_LAW_PCM[[0x55, 0xD5, 0x2A, 0xAA]].tolist() == [-8, 8, -32256, 32256]
    assert len(telephony.STEPS) == 89 and telephony.STEPS[[0, 44, 88]].tolist() == [7, 494, 32767]
    rng = np.random.default_rng(1)
    blocks = rng.integers(0, 256, (7, 64), dtype=np.uint8)
    blocks[:, 2] %= 89
    got = telephony.decode_adpcm(blocks)
    for b, mine in zip(blocks, got, strict=True):
        sample, index = int(b[0]) + 256 * int(b[1]) - (65536 if b[1] >= 128 else 0), int(b[2])
        want = [sample]
        for code in itertools.chain.from_iterable((x & 15, x >> 4) for x in map(int, b[4:])):
            step = int(telephony.STEPS[index])
            move = (step >> 3) + (step >> 2) * (code & 1) + (step >> 1) * (code >> 1 & 1) + step * (code >> 2 & 1)
            sample = max(-32768, min(32767, sample + (-move if code & 8 else move)))
            index = max(0, min(88, index + [-1, -1, -1, -1, 2, 4, 6, 8][code & 7]))
            want.append(sample)
        assert mine.tolist() == want


# -- 5


def test_bpe(docs):
    path = public_tokenizers.path("word_bpe_49k.json")
    library = Tokenizer.from_file(path)
    found = bpe.encode_documents(docs, path).collect()
    assert len(found) == len(rows())
    for r in found:
        want = next(ids for i, t, *_ in rows() if i == r["doc_id"] for ids in [library.encode(t or "", add_special_tokens=False).ids] if ids == r["ids"])
        text = library.decode(want, skip_special_tokens=False)
        assert r["decoded"] == text and r["n_tokens"] == len(want)
        assert r["ids_sha256"] == hashlib.sha256(np.array(want, "<u4").tobytes()).hexdigest() and r["decoded_sha256"] == hashlib.sha256(text.encode()).hexdigest()
    back = bpe.decode_documents(bpe.encode_documents(docs, path), path)
    assert sorted(r["decoded"] for r in back.collect()) == sorted(r["decoded"] for r in found)


def test_bpe_any_text():
    path = public_tokenizers.path("word_bpe_49k.json")
    library, mine = Tokenizer.from_file(path), bpe.PairIndexBpe(path)
    rng = random.Random(2)
    spans = [(32, 127), (0, 0x250), (0x370, 0x600), (0x1E00, 0x2100), (0x3000, 0xD7FF), (0xE000, 0x10FFFF)]
    texts = ["".join(chr(rng.randrange(*rng.choice(spans))) for _ in range(15)) for _ in range(1500)] + ["aaaa" * 40, "ΑΣ ΣΑΣ", "\x1cx\x1dy", "it's WE'LL 12½"]
    assert [x.tolist() for x in mine.encode_batch(texts)] == [e.ids for e in library.encode_batch(texts, add_special_tokens=False)]


# -- 6


def test_line_dedup_short_lines(spark):
    """Lines of few words go too when an earlier one equals them, or is near enough; blank lines stay."""
    data = [(1, "All rights reserved.\n}\n\nfour words are here"), (2, "all  rights reserved.\n\n}\nfour words are here now"), (3, "日本語の長い文章です。\nno no no no"), (4, "no\n日本語の長い文章です。\nfour words were here")]
    got = {r["doc_id"]: r["removed"] for r in line_dedup.removed_lines(spark.createDataFrame(data, "doc_id long, text string")).collect()}
    assert got == {1: [], 2: [0, 2, 3], 3: [], 4: [0, 1]}
    assert got == {d: g for (d, _), g in brute_lines(data, least=1).items()}


def brute_components(data, width, share):
    sets = []
    for i, t, *_ in data:
        w = WORD.findall(lower(t or ""))
        sets.append((i, {tuple(w[k : k + width]) for k in range(len(w) - width + 1)} if len(w) >= width else {tuple(w)} if w else set()))
    root = list(range(len(sets)))

    def top(k):
        while root[k] != k:
            k = root[k]
        return k

    for a, b in itertools.combinations(range(len(sets)), 2):
        x, y = sets[a][1], sets[b][1]
        if x and y and 100 * len(x & y) >= share * len(x | y):
            root[top(a)] = top(b)
    least = {}
    for k, (i, _) in enumerate(sets):
        if i is not None:
            least[top(k)] = min(i, least.get(top(k), i))
    return sorted(((i, len(s), least.get(top(k))) for k, (i, s) in enumerate(sets)), key=str)


def near_data(seed=7, n=60):
    rng = random.Random(seed)
    words = [f"w{k}" for k in range(300)]
    base = [rng.choices(words, k=rng.randrange(20, 90)) for _ in range(6)]
    data = []
    for i in range(n):
        text = list(rng.choice(base))
        for _ in range(rng.randrange(0, 3)):
            text[rng.randrange(len(text))] = rng.choice(words)
        data.append((i, " ".join(text)))
    return [*data, (None, "a b"), (200, "a b"), (201, "A  b"), (202, ""), (203, None), (204, "x"), data[0]]


@pytest.mark.parametrize("width,share,many", [(3, 90, 64), (5, 80, 64), (3, 90, 2), (5, 80, 2)])
def test_shingle_join(spark, monkeypatch, width, share, many):
    monkeypatch.setattr(shingle_join, "MANY", many)
    data = near_data()
    df = spark.createDataFrame(data, "doc_id long, text string")
    got = shingle_join.near_components(df, width=width, share=share).select("doc_id", "n_shingles", "component_id").collect()
    assert sorted(map(tuple, got), key=str) == brute_components(data, width, share)


def test_shingle_join_hub_of_several_sets(spark):
    """Sets of one prefix and size that don't link: a near copy of either one finds it, whichever comes first."""
    tails = [["common", "start", *(f"{side}{k}" for k in range(20))] for side in "AB"]
    texts = []
    for family in range(6):
        words = [f"f{family}w{k}" for k in range(100)]
        one, two = (words + tail for tail in tails)
        texts += [one, two, [*two[:-1], f"changed{family}"]]
    texts += [[f"other{k}x{j}" for j in range(5)] + tail for k in range(100) for tail in tails]
    data = [(i, " ".join(t)) for i, t in enumerate(texts)]
    want = brute_components(data, 3, 90)
    assert len({c for _, _, c in want}) == len(data) - 6
    got = shingle_join.near_components(spark.createDataFrame(data, "doc_id long, text string"), width=3, share=90).select("doc_id", "n_shingles", "component_id").collect()
    assert sorted(map(tuple, got), key=str) == want


def test_shingle_join_odd_rows(spark, docs):
    got = shingle_join.near_components(docs).select("doc_id", "n_shingles", "component_id").collect()
    assert sorted(map(tuple, got), key=str) == brute_components(rows(), 3, 90)
    kept = shingle_join.keep_one_of_each(spark.createDataFrame(near_data(), "doc_id long, text string")).collect()
    components = {c for _, n, c in brute_components(near_data(), 5, 80) if n}
    assert sorted(r["doc_id"] for r in kept if r["text"]) == sorted(components)


def test_keep_one_of_each_ids(spark):
    """Unrelated texts under one id are apart; near copies without ids are one group."""
    long = [f"w{k}" for k in range(60)]
    data = [(1, "one text of its own words"), (1, "quite another one with nothing alike"), (None, " ".join(long)), (None, " ".join([*long[:-1], "changed"])), (2, "")]
    kept = [r["text"] for r in shingle_join.keep_one_of_each(spark.createDataFrame(data, "doc_id long, text string")).collect()]
    assert len(kept) == 4 and {data[0][1], data[1][1], ""} < set(kept)


def test_connected_components(spark):
    rng = random.Random(3)
    links = [(rng.randrange(80), rng.randrange(80)) for _ in range(70)] + [(k, k + 1) for k in range(100, 160)]
    found = {r["node"]: r["root"] for r in graph.connected_components(spark.createDataFrame(links, "a long, b long")).collect()}
    root = {}
    top = lambda k: k if root.setdefault(k, k) == k else top(root[k])
    for a, b in links:
        if a != b:
            x, y = sorted((top(a), top(b)))
            root[y] = x
    assert found == {k: top(k) for k in root}


# -- 7


def test_token_counts(docs):
    path = public_tokenizers.path("piece_bpe_32k.model")
    cut = tokencount.processor(path)
    counts = Counter(i for _, t, *_ in rows() for w in WORD.findall(t or "") for i in cut.encode(w))
    assert {r["piece"]: r["n"] for r in tokencount.piece_counts(docs, path).collect()} == counts
    model = tokencount.learned_model(path, counts)
    assert model.scores["\u2581the"] > model.scores["\u2581without"]

    def best(word):
        w = tokencount.START + word
        values = [(0.0, 0, 0)]
        for n in range(1, len(w) + 1):
            score, pieces, fallback = values[n - 1]
            size = len(w[n - 1].encode())
            top = (score + size * model.byte_score, pieces - size, fallback - size)
            for k in range(max(0, n - 40), n):
                own = model.scores.get(w[k:n])
                if own is not None:
                    top = max(top, (values[k][0] + own, values[k][1] - 1, values[k][2]))
            values.append(top)
        return values[-1]

    found = sorted(map(tuple, tokencount.count_tokens(docs, path).collect()), key=str)
    want = []
    for i, t, *_ in rows():
        parts = [best(w) for w in WORD.findall(t or "")]
        want.append((i, len(parts), -sum(p[1] for p in parts), -sum(p[2] for p in parts), round(sum(p[0] for p in parts), 6)))
    for a, b in zip(found, sorted(want, key=str), strict=True):
        assert a[:4] == b[:4] and a[4] == pytest.approx(b[4], abs=1e-4)


# -- 8


def test_toxicity(spark, sf_dir):
    big = sf_dir.replace("0.001", "0.1")
    p = queries.op8_toxicity(spark, big).toPandas()
    labels = spark.read.parquet(f"{big}/labels.parquet").toPandas()
    q = p.merge(labels, on="doc_id")
    out = q[q["held_out"]]
    assert len(p) == 10_000 and p["score"].between(0, 1).all() and ((p["score"] >= 0.7) == (p["predicted"] == 1)).all()
    assert out["toxic"][out["predicted"] == 1].mean() > 0.9
    assert out["predicted"][out["toxic"] == 1].mean() > 0.4
    again = queries.op8_toxicity(spark, big).toPandas()
    assert p.sort_values("doc_id")["score"].tolist() == again.sort_values("doc_id")["score"].tolist()


def test_toxicity_scores_against_brute_force():
    """Windows, savings and score of a fitted model, recomputed in the plainest way."""
    import zstandard

    rng = random.Random(4)
    words = ["".join(rng.choice("abcdefgh") for _ in range(rng.randrange(2, 8))) for _ in range(300)]
    texts, labels = [], []
    for i in range(120):
        said = rng.choices(words, k=rng.randrange(10, 200))
        for _ in range(i % 2 * max(2, len(said) // 12)):
            said.insert(rng.randrange(len(said)), rng.choice(["vileword", "vilely", "nastyone"]))
        texts.append(toxicity.folded(" ".join(said)))
        labels.append(bool(i % 2))
    model = toxicity.fit(texts[:80], np.array(labels[:80]))
    assert model.dictionaries.toxic != model.dictionaries.ordinary and b"vile" in model.dictionaries.toxic and b"vile" not in model.dictionaries.ordinary

    def size(window, content):
        params = zstandard.ZstdCompressionParameters.from_level(5, min_match=3, write_content_size=False, write_checksum=False, write_dict_id=False, format=zstandard.FORMAT_ZSTD1_MAGICLESS)
        shared = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        shared.precompute_compress(compression_params=params)
        return len(zstandard.ZstdCompressor(dict_data=shared, compression_params=params).compress(window))

    scores = []
    for text in [*texts[80:], b"", b"x", b"long" * 100]:
        windows, held = [], b""
        for word in text.split():
            held += b" " + word
            if len(held) >= 48:
                windows, held = [*windows, held], b""
        windows = [*windows, held] if held else windows or [b" "]
        assert toxicity.windows(text) == windows
        d = model.dictionaries
        saved = sorted((size(w, d.ordinary + d.base) - size(w, d.toxic + d.base) for w in windows), reverse=True)
        n = len(saved)
        above = [sum(s > t for s in saved) for t in model.thresholds]
        x = [1, sum(saved) / n, *(sum(saved[:k]) / min(k, n) for k in (1, 2, 4, 8)), *(c / n for c in above), *(math.log(1 + c) for c in above), math.log(n)]
        want = 1 / (1 + math.exp(-sum(a * b for a, b in zip(x, model.weights, strict=True))))
        scores.append(float(model.score([toxicity.savings(d.compressors(), toxicity.windows(text))])[0]))
        assert scores[-1] == pytest.approx(want, abs=1e-9)
    toxic, plain = ([s for s, m in zip(scores, labels[80:]) if m == k] for k in (True, False))
    assert np.mean([a > b for a in toxic for b in plain]) > 0.8


def test_toxicity_one_class():
    model = toxicity.fit([b"one", b"two"], np.array([False, False]))
    assert 0 <= model.score([np.zeros(1)])[0] < 0.01
    assert toxicity.fit([], np.array([], bool)).score([np.zeros(1)])[0] < 0.01


def test_toxicity_odd_rows(spark, docs):
    labels = spark.createDataFrame([(i, 1, i % 2) for i in range(20)] + [(None, 1, 1), (3, 1, None), (3, 1, 1)], "doc_id long, quality int, toxic int")
    found = toxicity.score_documents(docs, toxicity.train(docs, labels)).collect()
    assert len(found) == len(rows()) and all(0 <= r["score"] <= 1 for r in found)


# -- 9


def test_warc(spark):
    data = [(1, "http://a/", "<p>x</p>"), (2, "http://b/\r\nX: y", "<p>x</p>"), (3, None, None), (4, "http://c/", ""), (5, "http://d/", "é" * 9), (6, "u", "y"), (6, "u", "y"), (None, "n", "y"), (7, "v", "WARC/1.1\r\n\r\n" * 50), (0, "z", "<p>x</p>")]
    pages = spark.createDataFrame([(*r, "clash") for r in data], "page_id long, url string, html string, digest string")
    found = sorted(map(tuple, warc.crawl_round_trip(pages).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to").collect()), key=str)
    import base64

    first = {}
    for i, _, h in data:
        if i is not None:
            first[h or ""] = min(i, first.get(h or "", i))
    want = []
    for i, _, h in data:
        raw = (h or "").encode()
        again = Counter((x[2] or "") for x in data)[h or ""] > 1 and i != first[h or ""]
        want.append((i, len(raw), base64.b32encode(hashlib.sha1(raw).digest()).decode(), "revisit" if again else "response", first[h or ""] if again else None))
    assert found == sorted(want, key=str)
    assert all(k == "response" for *_, k, _ in [tuple(r) for r in warc.crawl_round_trip(pages, min_bytes=10**6).select("page_id", "record_type", "refers_to").collect()])


def test_warc_text_ids(spark):
    data = [("b>\n1", "u", "same"), ("a é", "u", "same"), ("=7", "u", "other"), (None, None, None), ("7", "v", "same")]
    found = {r["page_id"]: (r["record_type"], r["refers_to"]) for r in warc.crawl_round_trip(spark.createDataFrame(data, "page_id string, url string, html string")).collect()}
    assert found == {"b>\n1": ("revisit", "7"), "a é": ("revisit", "7"), "7": ("response", None), "=7": ("response", None), None: ("response", None)}


def test_warc_normaliser():
    import gzip

    one = warc.record(1, "u", b"body\r\n\r\n", "D", "response", None, "2024-01-01T00:00:00Z")
    two = warc.record(2, "v", b"", "E", "revisit", 1, "2024-01-01T00:00:00Z")
    for content in (gzip.compress(one + two), gzip.compress(one) + gzip.compress(two), gzip.compress(one[:40]) + gzip.compress(one[40:] + b"\r\n" + two)):
        assert list(warc.records(warc.inflated(content))) == [one, two]
    with pytest.raises(ValueError):
        list(warc.records(warc.inflated(gzip.compress(one + two)[:-20])))


# -- 10


def brute_statistics(t):
    w = WORD.findall(t or "")
    times, marked = Counter(zip(w, w[1:], w[2:], strict=False)), set()
    for k in range(len(w) - 2):
        if times[w[k], w[k + 1], w[k + 2]] > 1:
            marked |= {k, k + 1, k + 2}
    lines = [x for x in (t or "").split("\n") if WORD.search(x)]
    return len(w), sum(map(len, w)), sum((t or "").count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), len(marked), len(lines)


def test_quality_statistics(docs):
    found = quality.text_statistics(docs).collect()
    assert sorted((str(r["doc_id"]), *(r[s] for s in quality.STATS)) for r in found) == sorted((str(i), *brute_statistics(t)) for i, t, *_ in rows())
    assert quality.judge(docs).count() == len(rows())


def brute_steps(x):
    """The minimum covariance determinant of the rows of x with the operator's bins, starts and floors, in numpy."""
    floors = np.array(quality.FLOORS)
    bins = lambda v: np.floor(v / quality.BIN)
    cut = lambda v, share: np.sort(bins(v))[max(0, math.ceil(share * len(v)) - 1)]
    distance = lambda mu, cov: np.einsum("ij,jk,ik->i", x - mu, np.linalg.inv(cov), x - mu)
    scatter = lambda rows: (rows - rows.mean(0)).T @ (rows - rows.mean(0)) / len(rows)
    med = np.array([(cut(x[:, k], 0.5) + 0.5) * quality.BIN for k in range(5)])
    mad = np.array([1.4826 * (cut(abs(x[:, k] - med[k]), 0.5) + 0.5) * quality.BIN for k in range(5)])
    s = np.sqrt(mad**2 + floors**2)
    z = (x - med) / s
    unit = z / np.sqrt((z * z).sum(1, keepdims=True))
    starts = [(med, np.diag(s**2)), (x.mean(0), scatter(x)), (med, np.outer(s, s) * (unit.T @ unit) / len(x) * 5), (med, np.outer(s, s) * scatter(np.tanh(z)))]
    ended = []
    for mu, cov in starts:
        cov, det = cov + np.diag(floors**2), np.inf
        while True:
            d = np.log2(distance(mu, cov) + 1e-9)
            near = x[bins(d) <= cut(d, quality.COVERAGE)]
            new = near.mean(0), scatter(near) + np.diag(floors**2)
            fell = np.linalg.slogdet(new[1])[1]
            if fell >= det - quality.LEAST_FALL:
                break
            (mu, cov), det = new, fell
        ended.append((det, mu, cov))
    det, mu, cov = min(ended, key=lambda e: e[0])
    near = x[distance(mu, cov * quality.consistency(quality.COVERAGE)) <= quality.chi2_value(quality.NEAR, 5)]
    return len(near), near.mean(0), (scatter(near) + np.diag(floors**2)) * quality.consistency(quality.NEAR)


def drawn(own, above):
    n, mu, cov = own
    mix = lambda a, b: (n * a + quality.PRIOR * b) / (n + quality.PRIOR)
    return n, mix(mu, above[1]), mix(cov, above[2])


def test_chi_squared():
    assert [round(quality.chi2_value(p, 5), 3) for p in (0.5, 0.75, 0.975, 0.999)] == [4.351, 6.626, 12.833, 20.515]


@pytest.mark.parametrize("most_units", [50_000, 0])
def test_quality_estimates(spark, monkeypatch, most_units):
    """The distributed steps against numpy, for units of 1 to 600 rows, with outliers that a plain scatter would hide."""
    monkeypatch.setattr(quality, "MOST_BROADCAST_UNITS", most_units)
    rng = np.random.default_rng(4)
    sizes = {"large": 600, "small": 40, "two": 2, "one": 1}
    data = {u: rng.normal([1.6, 0.3, 0.2, 0.3, 3.7], [0.05, 0.2, 0.3, 0.3, 0.6], (n, 5)) for u, n in sizes.items()}
    data["large"][:120] += [0, 2, 0, 1, 0]
    df = spark.createDataFrame([(u, *map(float, r)) for u, x in data.items() for r in x], "unit string, " + ", ".join(f"{f} double" for f in quality.FEATURES))
    found = {r["unit"]: r for r in quality.estimate(df.repartition(5)).collect()}
    for u, x in data.items():
        n, mu, cov = brute_steps(x)
        assert found[u]["n"] == n and np.allclose(found[u]["mu"], mu, rtol=1e-6, atol=1e-7), u
        assert np.allclose(quality.unpacked(found[u]["cov"]), cov, rtol=1e-6, atol=1e-7), u
    assert found["large"]["n"] <= 480


def quality_rows():
    rng = random.Random(8)
    words = ["alpha", "beta", "gamma", "delta", "of", "the", "#", "a&b", "zeta", "omega"] + [f"w{k}" for k in range(60)]
    out = []
    for i in range(240):
        text = "".join(rng.choice(words) + rng.choice([" ", " ", " ", "\n"]) for _ in range(rng.randrange(30, 160)))
        text = text.replace(" ", " #*$% ") if i % 17 == 0 else text
        text = text + "\nalpha beta gamma delta" * (i % 5)
        out.append((i, text, rng.choice(["en", "en", "de", None]), rng.choice(["s1", "s2", None]) if i % 40 else f"own{i}", i))
    return [*out, out[9], (None, None, None, None, None), (None, "", "en", "s1", 0)]


def brute_verdicts(data):
    stats = [brute_statistics(t) for _, t, *_ in data]
    failed = [s[0] < 50 or 100 * s[4] > 50 * s[0] for s in stats]
    share = lambda a, b: math.sqrt(min(a / max(b, 1), 4.0))
    x = np.array([(math.log(max(c, 1) / max(n, 1)), share(sym, n), share(dup, lines), share(rep, n), math.log(max(n, 1) / max(lines, 1))) for n, c, sym, dup, rep, lines in stats])
    ok = ~np.array(failed)
    pick_ = lambda f: brute_steps(x[[k for k in range(len(data)) if ok[k] and f(data[k])]])
    corpus, out = pick_(lambda r: True), {}
    for lang, source in {r[2:4] for k, r in enumerate(data) if ok[k]}:
        above = drawn(pick_(lambda r, lang=lang: r[2] == lang), corpus)
        _, mu, cov = drawn(pick_(lambda r, lang=lang, source=source: r[2:4] == (lang, source)), above)
        for k, r in enumerate(data):
            if ok[k] and r[2:4] == (lang, source):
                out[k] = float((x[k] - mu) @ np.linalg.inv(cov) @ (x[k] - mu))
    return failed, out


def test_quality_verdicts(spark):
    """Every verdict against brute force: all groups, groups of one document, null languages and sources, repeated rows."""
    data = quality_rows()
    df = spark.createDataFrame(data, "doc_id long, text string, lang string, source string, n_chars long").repartition(4)
    failed, distances = brute_verdicts(data)
    want = sorted((str(r[0]), failed[k], not failed[k] and distances[k] <= quality.CUTOFF) for k, r in enumerate(data))
    judged = quality.judge(df).collect()
    assert sorted((str(r["doc_id"]), r["base_failed"], r["kept"]) for r in judged) == want
    got = {r["doc_id"]: r["distance"] for r in judged if not r["base_failed"]}
    assert all(abs(got[data[k][0]] - d) < 1e-4 * max(1, d) for k, d in distances.items())
    assert 5 < sum(not kept and not bad for _, bad, kept in want) < 60
    odd = df.withColumnsRenamed({"lang": "gone", "text": "a.b"}).withColumn("lang", F.lit("x"))
    stays = quality.keep_good(odd, text_col="a.b", lang_col="gone")
    assert stays.columns == odd.columns and sorted(str(r["doc_id"]) for r in stays.collect()) == [i for i, _, kept in want if kept]


def test_quality_separates_labelled_documents(spark, sf_dir):
    big = sf_dir.replace("0.001", "0.1")
    q = queries.op10_quality(spark, big).toPandas().merge(spark.read.parquet(f"{big}/labels.parquet").toPandas(), on="doc_id")
    judged = q[~q["base_failed"]]
    assert judged["kept"][judged["quality"] == 1].mean() > 0.99
    assert judged["kept"][judged["quality"] == 0].mean() < 0.1


# -- shared


def test_word_stream():
    texts = [t for _, t, *_ in rows()]
    raw, at = utf8_buffer(pa.array(texts, pa.string()))
    got = word_stream(raw, at, lower=True).tobytes()
    assert got == b"".join(("".join(w + " " for w in WORD.findall(lower(t or ""))) + "\n").encode() for t in texts)
    assert json.dumps(len(got))
