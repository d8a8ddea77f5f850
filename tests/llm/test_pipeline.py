"""The corpus pipeline, stage by stage and as a whole, against brute force on a small table with nulls, repeats and columns
whose names the operators use themselves."""

import hashlib
import random
from collections import Counter

import duckdb
import numpy as np
import pandas as pd
import public_tokenizers
import pytest
from tokenizers import Tokenizer

import corpus_pipeline
from tests.llm.test_operators import WORD, brute_lines, brute_verdicts, lower
from waysite.llm import quality, queries

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, `row` string, own string, of int, copies int, gone string, removed string, tkey string, `a.b` string"


def documents():
    rng = random.Random(11)
    words = [f"w{k}" for k in range(400)] + ["of", "the", "and", "a&b"]
    line = lambda n: " ".join(rng.choice(words) for _ in range(n))
    shared = [line(12) for _ in range(4)]
    texts = []
    for i in range(70):
        lines = [line(rng.randrange(8, 20)) for _ in range(rng.randrange(6, 12))]
        lines.insert(rng.randrange(len(lines)), shared[i % 4] if i % 3 else shared[i % 4] + " more")
        texts.append("\n".join(lines))
    for i in range(20):
        words_of = texts[i % 6].split(" ")
        words_of[rng.randrange(len(words_of))] = f"z{i}"
        texts.append(" ".join(words_of))
    texts += [None, "", " \n\t", "too short", "# " * 80 + line(60), line(5) + "\n" + ("again and again " * 40)]
    rows = [(i, t, rng.choice(["en", "de", None]), rng.choice(["s1", "s2", "s2", None]), None if t is None else len(t)) for i, t in enumerate(texts)]
    rows += [rows[3], rows[3], (None, line(30) + "\n" + line(40), "en", "s1", 7), (None, None, None, None, None)]
    return [(*r, f"r{i}", "o", i, -1, "g", "x", "k", "dot") for i, r in enumerate(rows)]


def kept_by_quality(data):
    failed, distances = brute_verdicts(data)
    return [r for k, r in enumerate(data) if not failed[k] and distances[k] <= quality.CUTOFF]


def without_lines(data):
    gone, out = brute_lines(data), []
    for r in data:
        left = None if r[1] is None else "\n".join(x for k, x in enumerate(r[1].split("\n")) if k not in gone[r[:2]])
        if not (gone[r[:2]] and not WORD.search(left)):
            out.append((r[0], left, *r[2:4], None if r[4] is None else len(left), *r[5:]))
    return out


def one_of_each(data):
    sets = []
    for r in data:
        w = WORD.findall(lower(r[1] or ""))
        sets.append({tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set())
    root = list(range(len(data)))

    def top(k):
        while root[k] != k:
            k = root[k]
        return k

    for a in range(len(data)):
        for b in range(a):
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                root[top(a)] = top(b)
    best = {}
    for k, r in enumerate(data):
        group = top(k) if sets[k] else ("alone", r[:2])
        if group not in best or (r[0] is None, r[0] or 0) < (best[group][0] is None, best[group][0] or 0):
            best[group] = r
    return list(best.values())


def mixed(data):
    """By the SQL of the mixing operator; ids are one of a kind by now."""
    con = duckdb.connect()
    con.register("documents", pd.DataFrame([r[:4] for r in data], columns=["doc_id", "text", "lang", "source"]).astype({"doc_id": "Int64"}))
    copies = {i: n for i, n in con.sql(f"SELECT doc_id, copies FROM ({queries.OP2_SQL}) m").fetchall()}
    return [r for r in data for _ in range(copies[r[0]])]


def tokens(data):
    library = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    out = []
    for r in data:
        ids = library.encode(r[1] or "", add_special_tokens=False).ids
        out.append((r[0], len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(library.decode(ids, skip_special_tokens=False).encode()).hexdigest()))
    return out


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    at = str(tmp_path_factory.mktemp("pipeline"))
    spark.createDataFrame(documents(), SCHEMA).repartition(3).write.parquet(f"{at}/documents.parquet")
    return at


def content(rows):
    """Rows without the column that tells repeated ones apart."""
    return Counter((*r[:5], *r[6:7], *r[8:]) for r in map(tuple, rows))


def test_stages(spark, folder):
    docs, data = spark.read.parquet(f"{folder}/documents.parquet"), documents()
    for (_, stage), brute in zip(corpus_pipeline.STAGES[:4], (kept_by_quality, without_lines, one_of_each, mixed), strict=True):
        found, data = stage(spark, docs, folder), brute(data)
        assert found.columns == docs.columns and data
        assert content(found.collect()) == content(data), stage.__name__
        docs = found
    last = corpus_pipeline.STAGES[4][1](spark, docs, folder).select("doc_id", "n_tokens", "ids_sha256", "decoded_sha256")
    assert Counter(map(tuple, last.collect())) == Counter(tokens(data))


def test_run(spark, folder):
    data = documents()
    for brute in (kept_by_quality, without_lines, one_of_each, mixed):
        data = brute(data)
    found = corpus_pipeline.run(spark, folder).select("doc_id", "n_tokens", "ids_sha256", "decoded_sha256")
    assert Counter(map(tuple, found.collect())) == Counter(tokens(data))


def test_empty(spark, tmp_path):
    spark.createDataFrame([], SCHEMA).write.parquet(f"{tmp_path}/documents.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
