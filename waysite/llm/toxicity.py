"""Toxicity by compression distance: zstandard dictionaries of ordinary and of toxic text, compared window by window.

Two small dictionaries are trained alike and apart, one on windows of ordinary texts and one on windows of toxic ones. A
large base, trained on ordinary text, stands behind either, so that what both classes say is compressed alike with both. The
bytes by which the toxic dictionary makes a window shorter than the ordinary one are the window's saving. Training goes
on for a few rounds on the windows of each class that save most: those hold what is toxic in toxic texts, and what only
looks so in ordinary ones. Thresholds on savings are calibrated on ordinary windows, and a logistic curve turns their
counts into a score; both see only savings by dictionaries that were trained without the text."""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import pick, slices

#: A window is closed by the word that takes it to this many bytes.
WINDOW = 48
#: Shares of ordinary windows above each of the calibrated thresholds.
ABOVE = (0.01, 0.002, 0.0005)
#: Means of so many of a text's largest savings are features.
LARGEST = (1, 2, 4, 8)
#: Labelled texts of each class drawn for fitting at most, and the bytes of a text above which it is not drawn: 120 MB
#: are held by the driver at most.
SAMPLE, SAMPLE_BYTES = 3000, 20_000
BASE_BYTES, CLASS_BYTES = 128 << 10, 4 << 10
#: Rounds of training on the windows of each class that save most, and their share.
ROUNDS, MOST_SAVING = 2, 0.1
#: Parts of the labelled texts that are scored by dictionaries trained on the other parts.
FOLDS = 3
#: Compression level and shortest match.
LEVEL, SHORTEST = 5, 3
SLICE = 4 << 20


def folded(text: str | None) -> bytes:
    return (text or "").lower().encode()


def windows(text: bytes) -> list[bytes]:
    """Runs of whole words, each word after one space; a text without words has one window of a space."""
    out, words, size = [], [b""], 0
    for word in text.split():
        words.append(word)
        size += len(word) + 1
        if size >= WINDOW:
            out.append(b" ".join(words))
            words, size = [b""], 0
    if size or not out:
        out.append(b" ".join(words) if size else b" ")
    return out


def trained(samples: list[bytes], size: int, segment: int) -> bytes:
    """The content of a trained dictionary; of too few samples to train on, the samples themselves."""
    samples = [s for s in samples if len(s) >= 8]
    try:
        return zstandard.train_dictionary(size, samples, k=segment, d=8).as_bytes() if samples else b""
    except zstandard.ZstdError:
        return b"".join(samples)[-size:]


def compressor(content: bytes) -> zstandard.ZstdCompressor:
    params = zstandard.ZstdCompressionParameters.from_level(LEVEL, min_match=SHORTEST, write_content_size=False, write_checksum=False, write_dict_id=False, format=zstandard.FORMAT_ZSTD1_MAGICLESS)
    if not content:
        return zstandard.ZstdCompressor(compression_params=params)
    shared = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
    shared.precompute_compress(compression_params=params)
    return zstandard.ZstdCompressor(dict_data=shared, compression_params=params)


@dataclass(frozen=True)
class Dictionaries:
    base: bytes
    ordinary: bytes
    toxic: bytes

    def compressors(self) -> tuple[zstandard.ZstdCompressor, zstandard.ZstdCompressor]:
        return compressor(self.ordinary + self.base), compressor(self.toxic + self.base)


@dataclass(frozen=True)
class ToxicityModel:
    dictionaries: Dictionaries
    thresholds: tuple[float, ...]
    weights: tuple[float, ...]

    def score(self, saved: list[np.ndarray]) -> np.ndarray:
        x = np.array([features(s, self.thresholds) for s in saved])
        return 1 / (1 + np.exp(-np.clip(x @ np.array(self.weights), -30, 30)))


def savings(pair, cut: list[bytes]) -> np.ndarray:
    """Bytes that the toxic dictionary saves over the ordinary one on each window."""
    ordinary, toxic = pair
    return np.array([len(ordinary.compress(w)) - len(toxic.compress(w)) for w in cut])


def features(saved: np.ndarray, thresholds: tuple[float, ...]) -> list[float]:
    """1; the mean saving; means of the largest ones; for each threshold the share of windows above it and log(1 + their
    number); log(number of windows)."""
    top = np.sort(saved)[::-1].astype(float)
    counts = [int((saved > t).sum()) for t in thresholds]
    return [1.0, float(saved.mean()), *(float(top[:k].mean()) for k in LARGEST), *(c / len(saved) for c in counts), *(float(np.log1p(c)) for c in counts), float(np.log(len(saved)))]


def logistic(x: np.ndarray, y: np.ndarray, penalty: float = 1.0, steps: int = 40) -> np.ndarray:
    """Ridge-penalised logistic regression by Newton steps on standardised columns; the first column, which is 1, is not
    penalised. The weights are those of the columns as given."""
    mean, spread = x.mean(0), np.maximum(x.std(0), 1e-9)
    mean[0], spread[0] = 0.0, 1.0
    z = (x - mean) / spread
    w, ridge = np.zeros(x.shape[1]), np.diag([1e-6, *[penalty] * (x.shape[1] - 1)])
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        step = np.linalg.solve((z * (p * (1 - p))[:, None]).T @ z + ridge, z.T @ (y - p) - ridge @ w)
        w = w + step
        if np.abs(step).max() < 1e-9:
            break
    w = w / spread
    w[0] -= mean[1:] @ w[1:]
    return w


def most_saving(cut: list[bytes], saved: np.ndarray) -> list[bytes]:
    least = max(1.0, float(np.quantile(saved, 1 - MOST_SAVING))) if len(saved) else 1.0
    return [w for w, s in zip(cut, saved, strict=True) if s >= least] or cut


def train_dictionaries(toxic: list[list[bytes]], ordinary: list[list[bytes]]) -> Dictionaries:
    """From the windows of each toxic and each ordinary text. The texts are in two halves: the windows of one that go on
    are picked by dictionaries of the other, so what only one text says doesn't go on."""
    whole = [[[w for t in texts[half::2] for w in t] for texts in (toxic, ordinary)] for half in (0, 1)]
    base = trained([w for half in whole for w in half[1]], BASE_BYTES, 64)
    train = lambda chosen: Dictionaries(base, trained(chosen[1], CLASS_BYTES, 16), trained(chosen[0], CLASS_BYTES, 16))
    chosen = whole
    for _ in range(ROUNDS):
        pairs = [train(half).compressors() for half in chosen]
        chosen = [[most_saving(cut, savings(pair, cut)) for cut in half] for half, pair in zip(whole, reversed(pairs), strict=True)]
    return train([chosen[0][k] + chosen[1][k] for k in (0, 1)])


def fit(texts: list[bytes], labels: np.ndarray) -> ToxicityModel:
    """Dictionaries from all texts; thresholds and weights from texts scored by dictionaries of the other folds. Where a
    class is missing nothing can be learnt, and every text scores its share."""
    cut = [windows(t) for t in texts]
    of = lambda chosen, toxic: [c for c, f, m in zip(cut, chosen, labels, strict=True) if f and m == toxic]
    if not labels.any() or labels.all():
        share = np.clip(labels.mean() if len(labels) else 0.0, 1e-6, 1 - 1e-6)
        return ToxicityModel(Dictionaries(b"", b"", b""), tuple(0.0 for _ in ABOVE), (float(np.log(share / (1 - share))), *[0.0] * (len(LARGEST) + 2 * len(ABOVE) + 2)))
    # Folds are dealt within each class; a class of one text trains and calibrates on it.
    fold = np.zeros(len(texts), int)
    for m in (False, True):
        fold[labels == m] = np.arange((labels == m).sum()) % FOLDS
    saved: list[np.ndarray] = [np.zeros(1)] * len(texts)
    for k in range(FOLDS):
        rest = fold != k if (labels & (fold != k)).any() and (~labels & (fold != k)).any() else np.ones(len(texts), bool)
        pair = train_dictionaries(of(rest, True), of(rest, False)).compressors()
        for i in np.flatnonzero(fold == k):
            saved[i] = savings(pair, cut[i])
    plain = np.concatenate([s for s, m in zip(saved, labels, strict=True) if not m])
    thresholds = tuple(float(max(1.0, np.quantile(plain, 1 - share))) for share in ABOVE)
    weights = logistic(np.array([features(s, thresholds) for s in saved]), labels.astype(float))
    everything = np.ones(len(texts), bool)
    return ToxicityModel(train_dictionaries(of(everything, True), of(everything, False)), thresholds, tuple(float(v) for v in weights))


def train(docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", label_id: str = "doc_id", label_col: str = "toxic", sample: int = SAMPLE, sample_bytes: int = SAMPLE_BYTES) -> ToxicityModel:
    """Fit on at most `sample` labelled texts of each class, drawn by a hash of the id, of the rows whose crc32(id as
    text) mod 3 is not 1. Texts of more than `sample_bytes` bytes take no part in fitting, so that the driver holds
    2 * sample * sample_bytes bytes at most; they are scored like all others. Null labels, ids and texts are left out; a
    document labelled twice counts as toxic if either is 1."""
    marks = pick(labels, id=label_id, toxic=label_col).dropna().groupBy("id").agg((F.max("toxic") == 1).alias("toxic"))
    crc = F.crc32(F.col("id").cast("string").cast("binary"))
    known = marks.where(F.pmod(crc, F.lit(3)) != 1).withColumn("at", F.md5(F.col("id").cast("string")))
    drawn = known.where("toxic").orderBy("at").limit(sample).unionAll(known.where("not toxic").orderBy("at").limit(sample)).select("id", "toxic", "at")
    texts = pick(docs, doc_id=id_col, text=text_col).where(F.octet_length("text") <= sample_bytes)
    # At most 2 * sample rows of a few bytes: a proven bound. An id that repeats gives its smallest text.
    met = texts.join(F.broadcast(drawn), F.col("doc_id") == F.col("id")).groupBy("id").agg(F.min("text").alias("text"), F.first("toxic").alias("toxic"), F.first("at").alias("at"))
    rows = met.select("at", "text", "toxic").toPandas().sort_values("at")
    return fit([folded(t) for t in rows["text"]], rows["toxic"].to_numpy(bool))


def score_documents(docs: DataFrame, model: ToxicityModel, *, id_col: str = "doc_id", text_col: str = "text", cut: float = 0.7) -> DataFrame:
    """docs -> (doc_id, held_out, score, predicted, n_windows, hot_windows), a row for every input row.

    Whole texts; null counts as the empty text, which is one window. held_out: crc32(id as text; null: empty) mod 3 is 1.
    hot_windows: those above the first threshold. Only the text enters the score; equal texts score alike."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pair = model.dictionaries.compressors()
        for batch in slices(batches, "text", SLICE):
            ids, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            saved = [savings(pair, windows(folded(t))) for t in texts]
            score = model.score(saved)
            held = [zlib.crc32(b"" if i is None else str(i).encode()) % 3 == 1 for i in ids]
            hot = [int((s > model.thresholds[0]).sum()) for s in saved]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(held), pa.array(score), pa.array((score >= cut).astype(np.int32)), pa.array([len(s) for s in saved], pa.int64()), pa.array(hot, pa.int64())], names=["doc_id", "held_out", "score", "predicted", "n_windows", "hot_windows"])

    chosen = pick(docs, doc_id=id_col, text=text_col)
    return chosen.mapInArrow(run, f"doc_id {chosen.schema['doc_id'].dataType.simpleString()}, held_out boolean, score double, predicted int, n_windows long, hot_windows long")
