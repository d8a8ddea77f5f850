"""Covers by few sites with one score a path, as bits: what a path holds is which sites cover it.

Paths that the same sites cover gain alike, so a placement needs only the different rows of bits and the sum of their
scores, whatever the number of paths."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from waysite.sources.tables import discard, materialize

#: Sites that are still bits, 64 a column; bytes of rows that one process takes.
MOST_BIT_SITES, MOST_BIT_BYTES = 1_024, 96 << 20


@dataclass(frozen=True)
class SiteBits:
    """rows(path_id, score, w0, w1, ...): bit i of the words, 64 each, tells whether ids[i] covers the path."""

    rows: DataFrame
    ids: np.ndarray

    @property
    def words(self) -> list[str]:
        return [f"w{j}" for j in range(-(-len(self.ids) // 64))]

    def merged(self) -> tuple[np.ndarray, np.ndarray] | None:
        """(words, sum of scores) of the different rows of bits; None if they are too many for one process."""
        return self.taken(self.rows.groupBy(*self.words).agg(F.sum("score").alias("score")).select("score", *self.words))

    def by_path(self) -> tuple[np.ndarray, np.ndarray, np.ndarray] | None:
        """(path ids, words, scores), or None alike."""
        found = self.taken(self.rows.select("score", "path_id", *self.words))
        return None if found is None else (found[0][:, 0].copy(), np.ascontiguousarray(found[0][:, 1:]), found[1])

    @staticmethod
    def taken(rows: DataFrame) -> tuple[np.ndarray, np.ndarray] | None:
        most = MOST_BIT_BYTES // (8 * len(rows.columns))
        held = materialize(rows, "bits-taken")
        try:
            if held.count() > most:
                return None
            table = held.toArrow()
        finally:
            discard(held)
        return np.stack([table.column(k).to_numpy() for k in range(1, table.num_columns)], 1), table.column(0).to_numpy()

    def discard(self) -> None:
        discard(self.rows)


def site_bits(cover: DataFrame) -> SiteBits | None:
    """cover(path_id, site_id, score) as bits; None if its sites are too many, if the sites of a path differ in score or a
    pair is there twice."""
    held = cover.select(*(F.col(c).cast("long").alias(c) for c in ("path_id", "site_id", "score")))
    ids = np.sort(held.select("site_id").distinct().limit(MOST_BIT_SITES + 1).toArrow().column(0).to_numpy())
    if not 0 < len(ids) <= MOST_BIT_SITES:
        return None
    marks = cover.sparkSession.createDataFrame([(int(s), i >> 6, int(np.uint64(1 << (i & 63)).astype(np.int64))) for i, s in enumerate(ids)], "m_site long, word int, mark long")
    marked = held.join(F.broadcast(marks), F.col("site_id") == F.col("m_site"))
    out = SiteBits(None, ids)
    own = [F.bit_or(F.when(F.col("word") == j, F.col("mark")).otherwise(F.lit(0))).alias(w) for j, w in enumerate(out.words)]
    each = marked.groupBy("path_id").agg(F.min("score").alias("score"), F.max("score").alias("most"), F.count("*").alias("number"), *own)
    rows = materialize(each, "cover-bits")
    set_bits = sum((F.bit_count(w) for w in out.words), F.lit(0))
    if rows.where((F.col("score") != F.col("most")) | (F.col("number") != set_bits)).limit(1).count():
        discard(rows)
        return None
    kept = rows.select("path_id", "score", *out.words)
    kept.written_at = rows.written_at
    return SiteBits(kept, ids)


def has_bit(words: np.ndarray, i: int) -> np.ndarray:
    return (words[:, i >> 6] >> (i & 63)) & 1 == 1


def bit_sums(words: np.ndarray, score: np.ndarray, n: int) -> np.ndarray:
    """Over the rows that have each of the first n bits, the sum of scores."""
    return np.array([int(score[has_bit(words, i)].sum()) for i in range(n)], np.int64)


def sketched_bits(bits: SiteBits, members: DataFrame, pairs: list[tuple[int, int]], prime: int) -> np.ndarray:
    """For each site and hash (a, b) the word of its paths' marks, made of members(path_id, route); rows of bits whose paths'
    hashes end alike are ORed."""
    f, width = len(pairs), len(bits.words)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = np.zeros((f, 32, width), np.int64)
        for batch in batches:
            if not batch.num_rows:
                continue
            paths = batch.column(0).to_numpy() % prime
            words = np.stack([batch.column(1 + j).to_numpy() for j in range(width)], 1)
            for c, (a, b) in enumerate(pairs):
                h = (a * paths + b) % prime
                place = np.where(h == 0, 31, np.bitwise_count((h & -h) - 1)).astype(np.int64)
                order = np.argsort(place, kind="stable")
                first = np.flatnonzero(np.r_[True, np.diff(place[order]) > 0])
                held[c, place[order][first]] |= np.bitwise_or.reduceat(words[order], first, axis=0)
        c, p = np.nonzero(held.any(2))
        yield pa.RecordBatch.from_arrays([pa.array(c * 32 + p, pa.int64()), pa.array([held[i, j].tobytes() for i, j in zip(c, p, strict=True)], pa.binary())], ["at", "bits"])

    met = members.select(F.col("path_id").cast("long").alias("member"), F.col("route").cast("long").alias("r")).join(bits.rows, F.col("r") == F.col("path_id")).select("member", *bits.words)
    out = np.zeros((len(bits.ids), f), np.int64)
    for row in met.mapInArrow(run, "at long, bits binary").collect():
        words = np.frombuffer(row["bits"], np.int64)
        on = np.array([(int(words[i >> 6]) >> (i & 63)) & 1 for i in range(len(bits.ids))], np.int64)
        out[:, row["at"] // 32] |= on << (row["at"] % 32)
    return out
