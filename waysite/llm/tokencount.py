"""Token counts under a unigram model, by dynamic programming over a trie of distinct pre-tokens.

The pre-tokens of a slice are inserted into one trie of characters. Forward scores (the best log-probability of a
segmentation of the prefix, and its number of pieces) are computed once per trie node, so words that share a prefix
share its work; a terminal node stores the counts of its word. Documents then only sum stored counts."""

from __future__ import annotations

import math
import uuid
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import pick, segments, slices, utf8_buffer, word_stream

SLICE = 4 << 20
#: Words remembered by a worker with their counts: bounds its memory, not what is counted.
REMEMBERED = 600_000
START = "▁"


class TrieUnigram:
    """Pieces with log-probabilities; a character that no piece covers costs its UTF-8 bytes, each a piece.

    piece_scores: {piece: log-probability}; byte_score: that of a fallback byte. A word is written with START before
    it. Of segmentations with equal scores the one with fewer pieces wins."""

    def __init__(self, piece_scores: dict[str, float], byte_score: float):
        self.scores, self.byte_score = piece_scores, byte_score
        # Every ending of a piece, with the score of those that are pieces: a longer ending of an unknown one is none.
        self.endings: dict[str, float | None] = {}
        for piece in piece_scores:
            for k in range(len(piece)):
                self.endings.setdefault(piece[k:], None)
        self.endings.update(piece_scores)
        self.known: dict[str, tuple[int, int, float]] = {}

    def count_words(self, words: list[str]) -> list[tuple[int, int, float]]:
        """For each distinct word (pieces, of which fallback bytes, log-probability)."""
        root: dict = {}
        for word in words:
            node = root
            for c in word:
                node = node.setdefault(c, {})
            node[""] = word  # terminal
        out: dict[str, tuple[int, int, float]] = {}
        # Depth first; best[d] and path[:d] are the forward values and characters of the prefix of length d at hand.
        best, path = [(0.0, 0, 0)], []
        stack = [(root, 0, START)]
        while stack:
            node, depth, c = stack.pop()
            del best[depth + 1 :], path[depth:]
            path.append(c)
            best.append(self._step(best, path))
            for longer, child in node.items():
                if longer == "":
                    score, pieces, fallback = best[-1]
                    out[child] = (-pieces, -fallback, score)
                else:
                    stack.append((child, depth + 1, longer))
        return [out[w] for w in words]

    def _step(self, best: list, path: list[str]) -> tuple[float, int, int]:
        """The forward value of the whole path, from those of its shorter prefixes: (score, -pieces, -fallback bytes)."""
        n, last = len(path), path[-1]
        score, pieces, fallback = best[n - 1]
        size = 1 if last < "\x80" else len(last.encode())
        top = (score + size * self.byte_score, pieces - size, fallback - size)
        ending, endings = "", self.endings
        for k in range(n - 1, -1, -1):
            ending = path[k] + ending
            if ending not in endings:
                break
            own = endings[ending]
            if own is not None:
                score, pieces, fallback = best[k]
                found = (score + own, pieces - 1, fallback)
                if found > top:
                    top = found
        return top

    def lookup(self, words: list[str]) -> list[tuple[int, int, float]]:
        if len(self.known) + len(words) > REMEMBERED:
            self.known = {w: self.known[w] for w in words if w in self.known}
        fresh = [w for w in words if w not in self.known]
        self.known.update(zip(fresh, self.count_words(fresh), strict=True))
        return [self.known[w] for w in words]


@lru_cache(maxsize=2)
def processor(path: str):
    import sentencepiece

    return sentencepiece.SentencePieceProcessor(model_file=path)


def piece_counts(docs: DataFrame, model_path: str, *, text_col: str = "text") -> DataFrame:
    """(piece, n): how often each piece stands in all texts when every word is cut as the file itself cuts it. Words are
    cut once a task, or as often as it can't hold them all; counts are summed per task, then by piece, of which there are as many as the file has."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = processor(model_path)
        total, waiting = np.zeros(model.get_piece_size(), np.int64), Counter()

        def cut() -> None:
            ids = model.encode(list(waiting), num_threads=1) if waiting else []
            flat = np.fromiter((i for x in ids for i in x), np.int64)
            times = np.repeat(np.fromiter(waiting.values(), np.int64, len(waiting)), [len(x) for x in ids])
            total[:] += np.bincount(flat, weights=times, minlength=len(total)).astype(np.int64)
            waiting.clear()

        for batch in slices(batches, "text", SLICE):
            array, _ = segments(word_stream(*utf8_buffer(batch.column(0)), lower=False))
            encoded = pc.dictionary_encode(array)
            times = np.bincount(np.asarray(encoded.indices), minlength=len(encoded.dictionary))
            for word, n in zip(encoded.dictionary.to_pylist(), times.tolist(), strict=True):
                waiting[word[:-1].decode("utf-8", "replace")] += n
            if len(waiting) > REMEMBERED:
                cut()
        cut()
        held = np.flatnonzero(total)
        if len(held):
            yield pa.RecordBatch.from_arrays([pa.array(held.astype(np.int32)), pa.array(total[held])], names=["piece", "n"])

    return pick(docs, text=text_col).mapInArrow(run, "piece int, n long").groupBy("piece").agg(F.sum("n").alias("n"))


def learned_model(model_path: str, counts: dict[int, int]) -> TrieUnigram:
    """The pieces of a sentencepiece file as a unigram model: log-probabilities from their counts in the texts, each one
    higher than counted so that none is 0. Fallback bytes share what is counted of them."""
    model = processor(model_path)
    ids = [i for i in range(model.get_piece_size()) if not (model.is_byte(i) or model.is_control(i) or model.is_unknown(i))]
    loose = sum(n for i, n in counts.items() if model.is_byte(i) or model.is_unknown(i))
    total = math.log(sum(counts.get(i, 0) + 1 for i in ids) + loose + 256)
    return TrieUnigram({model.id_to_piece(i): math.log(counts.get(i, 0) + 1) - total for i in ids}, math.log((loose + 256) / 256) - total)


#: The model that this worker uses, by the name of the run it belongs to: its remembered words serve all its tasks.
_held: dict[str, TrieUnigram] = {}


def held_model(run: str, model_path: str, counts: dict[int, int]) -> TrieUnigram:
    if run not in _held:
        _held.clear()
        _held[run] = learned_model(model_path, counts)
    return _held[run]


def count_tokens(docs: DataFrame, model_path: str, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs -> (doc_id, n_words, n_tokens, n_fallback, log_score), a row for every input row. The weights of the pieces
    are learned from all the texts first.

    Words are runs of bytes other than white space (the six ASCII ones). n_tokens: pieces of the best segmentation of
    every word; n_fallback: those that are single bytes; log_score: sum of the words' natural log-probabilities,
    rounded to 6 places. Null and empty texts give zeros."""

    counts = {r["piece"]: r["n"] for r in piece_counts(docs, model_path, text_col=text_col).collect()}  # a number a piece
    shared, name = docs.sparkSession.sparkContext.broadcast(counts), uuid.uuid4().hex

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = held_model(name, model_path, shared.value)
        for batch in slices(batches, "text", SLICE):
            array, ends = segments(word_stream(*utf8_buffer(batch.column(1)), lower=False))
            encoded = pc.dictionary_encode(array)
            words = [w[:-1].decode("utf-8", "replace") for w in encoded.dictionary.to_pylist()]
            at = np.asarray(encoded.indices)
            counts = np.array([(0, 0, 0.0) if not w else found for w, found in zip(words, model.lookup(words), strict=True)], float).reshape(-1, 3)
            rows = np.flatnonzero(ends)
            starts = np.concatenate([[0], rows[:-1] + 1]).astype(np.int64) if len(rows) else rows
            sums = [np.add.reduceat(counts[at, k], starts) if len(rows) else np.zeros(0) for k in range(3)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rows - starts, pa.int64()), pa.array(sums[0].astype(np.int64)), pa.array(sums[1].astype(np.int64)), pa.array(np.round(sums[2], 6))], names=["doc_id", "n_words", "n_tokens", "n_fallback", "log_score"])

    chosen = pick(docs, doc_id=id_col, text=text_col)
    return chosen.mapInArrow(run, f"doc_id {chosen.schema['doc_id'].dataType.simpleString()}, n_words long, n_tokens long, n_fallback long, log_score double")
