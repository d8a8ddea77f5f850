"""BPE encoding and decoding with a pair occurrence index.

The distinct pre-tokens of a partition are laid out in one array of symbols. An index maps every mergeable pair to
all its positions; the active ranks are taken in ascending order, every position of the rank is merged in one go and
the index gets the pairs that the merge made. So a pair is looked up once for a whole partition, and a pre-token is
encoded once however often it occurs."""

from __future__ import annotations

import hashlib
import heapq
import json
import unicodedata
from array import array
from collections.abc import Iterator
from functools import lru_cache
from itertools import chain

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from tokenizers import Regex, Tokenizer
from tokenizers.pre_tokenizers import Split

from .common import pick, slices

#: Text bytes encoded at once, and distinct pre-tokens remembered by a task: both bound the memory of a worker.
SLICE, REMEMBERED = 2 << 20, 400_000
#: All but Latin letters and common punctuation.
UNSETTLED = regex.compile("[^\x00-\u024f\u2010-\u2027\u20ac]")


def byte_characters() -> dict[int, str]:
    """The printable character that byte-level vocabularies write for each byte: itself if it is visible Latin-1, or
    else the next free character from 256 on."""
    visible = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    hidden = (b for b in range(256) if b not in visible)
    return {b: chr(b) for b in visible} | {b: chr(256 + i) for i, b in enumerate(hidden)}


class PairIndexBpe:
    """A tokenizer of the kind described by word_bpe_49k.json: NFC, runs of white space to one space, lower case, a
    splitting pattern, bytes as characters, merges with a suffix on the last symbol of a word, special tokens."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        self.vocab: dict[str, int] = model["vocab"]
        self.suffix: str = model.get("end_of_word_suffix") or ""
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.text_of = {i: t for t, i in self.vocab.items()} | {i: t for t, i in self.special.items()}
        self.merges: dict[tuple[int, int], tuple[int, int]] = {}
        for rank, (left, right) in enumerate(model["merges"]):
            self.merges[self.vocab[left], self.vocab[right]] = (rank, self.vocab[left + right])
        self.pairs = [None] * len(self.merges)
        for pair, (rank, _) in self.merges.items():
            self.pairs[rank] = pair
        split = next(p["pattern"]["Regex"] for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")
        self.words = regex.compile(split)
        self.marks = regex.compile("|".join(map(regex.escape, sorted(self.special, key=len, reverse=True)))) if self.special else None
        self.byte_char = byte_characters()
        # Symbols of single bytes: 0 to 255 within a word, 256 to 511 at its end.
        self.byte_ids = np.array([self.vocab[self.byte_char[b] + end] for end in ("", self.suffix) for b in range(256)])
        self.byte_ranks = np.full((512, 512), -1, np.int64)
        place = {int(i): k for k, i in enumerate(self.byte_ids)}
        for (left, right), (rank, _) in self.merges.items():
            if left in place and right in place:
                self.byte_ranks[place[left], place[right]] = rank
        self.known: dict[str | int, bytes] = {}
        self.library_split = Split(Regex(split), "removed", invert=True)
        self.library_form = Tokenizer.from_file(path).normalizer

    # -- text to pre-tokens

    def normalize(self, text: str) -> str:
        """NFC and lower case; runs of white space need no change, as the pattern leaves out all of it."""
        if not text.isascii():
            text = unicodedata.normalize("NFC", text)
        return text.lower()

    def pieces(self, text: str) -> list[str | int]:
        """Pre-tokens of a text in order, special tokens as their ids."""
        if self.marks is None or "<|" not in text:
            return self.cut(text)
        out: list[str | int] = []
        start = 0
        for m in self.marks.finditer(text):
            out += self.cut(text[start : m.start()])
            out.append(self.special[m[0]])
            start = m.end()
        out += self.cut(text[start:])
        return out

    def cut(self, text: str) -> list[str]:
        """Normalise and split; scripts whose character classes differ between Unicode versions go by the library's."""
        if UNSETTLED.search(text):
            return [w for w, _ in self.library_split.pre_tokenize_str(self.library_form.normalize_str(text))]
        return self.words.findall(self.normalize(text))

    # -- pre-tokens to ids

    def encode_words(self, words: list[str]) -> list[tuple[int, ...]]:
        """The ids of distinct pre-tokens, all encoded together through the pair index."""
        if not words:
            return []
        data = [w.encode() for w in words]
        ends = np.cumsum(np.fromiter(map(len, data), np.int64, len(data)))
        codes = np.frombuffer(b"".join(data), np.uint8).astype(np.int64)
        codes[ends - 1] += 256
        symbols = self.byte_ids[codes].tolist()
        self._merge_all(symbols, codes, ends)
        bounds = [0, *ends.tolist()]
        return [tuple([s for s in symbols[a:b] if s >= 0]) for a, b in zip(bounds, bounds[1:], strict=False)]

    def _merge_all(self, symbols: list[int], codes: np.ndarray, ends: np.ndarray) -> None:
        n, merges = len(symbols), self.merges
        following, before = np.arange(1, n + 1), np.arange(-1, n - 1)
        following[ends - 1], before[0], before[ends[:-1]] = -1, -1, -1
        # The index of the first pairs: positions grouped by rank, of those pairs of bytes that any rule merges.
        rank = self.byte_ranks[codes[:-1], codes[1:]]
        rank[ends[:-1] - 1] = -1
        places = np.flatnonzero(rank >= 0)
        places = places[np.argsort(rank[places], kind="stable")]
        active, starts = np.unique(rank[places], return_index=True)
        active = active.tolist()
        index: dict[int, list[int]] = dict(zip(active, (x.tolist() for x in np.split(places, starts[1:])), strict=False)) if active else {}
        following, before = following.tolist(), before.tolist()
        while active:
            rank = heapq.heappop(active)
            left, right = self.pairs[rank]
            made = merges[left, right][1]
            places = index.pop(rank)
            places.sort()
            for k, i in enumerate(places):
                j = following[i]
                if j < 0 or symbols[i] != left or symbols[j] != right:
                    continue  # one of the two was merged with its other neighbour meanwhile
                symbols[i], symbols[j] = made, -1
                after, prior = following[j], before[i]
                following[i], following[j] = after, -1
                lower = False
                if after >= 0:
                    before[after] = i
                    if found := merges.get((made, symbols[after])):
                        lower |= self._note(index, active, found[0], i) < rank
                if prior >= 0 and (found := merges.get((symbols[prior], made))):
                    lower |= self._note(index, active, found[0], prior) < rank
                if lower and k + 1 < len(places):  # a lower rank became active: it goes first, the rest waits
                    for p in places[k + 1 :]:
                        self._note(index, active, rank, p)
                    break

    @staticmethod
    def _note(index: dict[int, list[int]], active: list[int], rank: int, place: int) -> int:
        if rank in index:
            index[rank].append(place)
        else:
            index[rank] = [place]
            heapq.heappush(active, rank)
        return rank

    def encode_batch(self, texts: list[str]) -> list[np.ndarray]:
        """The ids of each text; pre-tokens not remembered are encoded once for all texts."""
        cut = [self.pieces(t) for t in texts]
        wanted = set(chain.from_iterable(cut))
        self.known = recent(self.known, wanted)
        new = wanted - self.known.keys()
        words = sorted(w for w in new if w.__class__ is str)
        self.known.update((w, array("I", ids).tobytes()) for w, ids in zip(words, self.encode_words(words), strict=True))
        self.known.update((w, array("I", (w,)).tobytes()) for w in new if w.__class__ is int)
        return [np.frombuffer(b"".join(map(self.known.__getitem__, parts)), "<u4") for parts in cut]

    def decode(self, ids) -> str:
        """As the library does where no decoder is set: the tokens' strings joined by single spaces."""
        return " ".join(map(self.text_of.__getitem__, ids.tolist() if isinstance(ids, np.ndarray) else ids))


def recent(known: dict, wanted: set) -> dict:
    """What is remembered, or, once that and the wanted would be too much, what of it is wanted now."""
    return known if len(known) + len(wanted) <= REMEMBERED else {k: known[k] for k in wanted & known.keys()}


@lru_cache(maxsize=2)
def tokenizer(path: str) -> PairIndexBpe:
    """One tokenizer a worker process, so that its tasks share the pre-tokens encoded so far."""
    return PairIndexBpe(path)


def encode_documents(docs: DataFrame, tokenizer_path: str, *, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = True) -> DataFrame:
    """docs -> (doc_id, n_tokens, ids_sha256, decoded_sha256[, ids, decoded]), a row for every input row.

    Whole texts; null and empty texts have no ids and decode to the empty text. The tokenizer file is read by every
    executor from tokenizer_path."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = tokenizer(tokenizer_path)
        for batch in slices(batches, "text", SLICE):
            encoded = bpe.encode_batch([t or "" for t in batch.column(1).to_pylist()])
            decoded = [bpe.decode(ids) for ids in encoded]
            digest = [hashlib.sha256(ids.tobytes()).hexdigest() for ids in encoded]
            text_digest = [hashlib.sha256(t.encode()).hexdigest() for t in decoded]
            columns = [batch.column(0), pa.array([len(ids) for ids in encoded], pa.int64()), pa.array(digest, pa.string()), pa.array(text_digest, pa.string())]
            names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
            if with_ids:
                columns += [pa.array(encoded, pa.list_(pa.int32())), pa.array(decoded, pa.string())]
                names += ["ids", "decoded"]
            yield pa.RecordBatch.from_arrays(columns, names=names)

    chosen = pick(docs, doc_id=id_col, text=text_col)
    more = ", ids array<int>, decoded string" if with_ids else ""
    return chosen.mapInArrow(run, f"doc_id {chosen.schema['doc_id'].dataType.simpleString()}, n_tokens long, ids_sha256 string, decoded_sha256 string{more}")


def decode_documents(encoded: DataFrame, tokenizer_path: str, *, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """(doc_id, ids) -> (doc_id, decoded); null ids decode to the empty text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = tokenizer(tokenizer_path)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([bpe.decode(ids or []) for ids in batch.column(1).to_pylist()], pa.string())], names=["doc_id", "decoded"])

    chosen = pick(encoded, doc_id=id_col, ids=ids_col)
    return chosen.mapInArrow(run, f"doc_id {chosen.schema['doc_id'].dataType.simpleString()}, decoded string")
