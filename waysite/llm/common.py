"""Helpers shared by the training-data operators: input selection, shared-folder tables, Arrow and numpy kernels."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from waysite.sources.tables import discard, materialize, read_table, shared_dir  # noqa: F401

#: A word is a run of bytes other than space, tab, line feed, vertical tab, form feed and carriage return.
SPACES = "\\x20\\x09-\\x0D"
SPACE_CLASS = f"[{SPACES}]+"
WORD_CLASS = f"[^{SPACES}]+"
#: The same six characters as a literal, for trim().
SPACE_CHARS = " \t\n\x0b\x0c\r"

_IS_SPACE = np.zeros(256, bool)
_IS_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[0x41:0x5B] += 0x20


def named(df: DataFrame, column: str) -> Column:
    """A column of df by its whole name, dots and backticks included."""
    return df["`" + column.replace("`", "``") + "`"]


def pick(df: DataFrame, **wanted: str) -> DataFrame:
    """Only the named columns under the operator's own names, so that extra or clashing input columns never matter."""
    return df.select(*(named(df, column).alias(name) for name, column in wanted.items()))


def text_key(text: Column) -> Column:
    """The hash that names a text; null counts as the empty text."""
    return F.xxhash64(F.coalesce(text, F.lit("")))


def lower_ascii(text: Column) -> Column:
    """Lower-case A-Z only (lower() would also change other letters)."""
    return F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def word_count(text: Column) -> Column:
    """Number of words, as built-in functions; null counts as the empty text."""
    trimmed = F.regexp_replace(F.coalesce(text, F.lit("")), f"^{SPACE_CLASS}|{SPACE_CLASS}$", "")
    return F.when(trimmed == "", F.lit(0)).otherwise(F.size(F.split(trimmed, SPACE_CLASS))).cast("long")


def slices(batches: Iterator[pa.RecordBatch], column: str, limit: int) -> Iterator[pa.RecordBatch]:
    """Cut Arrow batches so that one holds about `limit` bytes of `column` at most (a longer row stands alone)."""
    for batch in batches:
        array = batch.column(batch.schema.get_field_index(column))
        lengths = np.nan_to_num(_lengths(array))
        start, room = 0, 0
        for i, n in enumerate(lengths.tolist()):
            if i > start and room + n > limit:
                yield batch.slice(start, i - start)
                start, room = i, 0
            room += n
        if start < batch.num_rows:
            yield batch.slice(start)


def _lengths(array: pa.Array) -> np.ndarray:
    import pyarrow.compute as pc

    return pc.fill_null(pc.binary_length(array), 0).to_numpy(zero_copy_only=False)


def utf8_buffer(array: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The UTF-8 bytes of a string array (null: empty) and their n+1 offsets."""
    import pyarrow.compute as pc

    array = pc.fill_null(array, "") if array.null_count else array
    array = array.cast(pa.large_string())
    _, offsets, data = array.buffers()
    n = len(array)
    at = np.frombuffer(offsets, np.int64, n + 1, array.offset * 8) if n else np.zeros(1, np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[at[0] : at[-1]], at - at[0]


def word_stream(raw: np.ndarray, offsets: np.ndarray, lower: bool) -> np.ndarray:
    """Texts as one byte stream: each word followed by 0x20, each text by 0x0A.

    Words hold neither byte, so the stream can be cut back into texts and words without offsets."""
    n = len(offsets) - 1
    out = np.full(len(raw) + 2 * n, 0x20, np.uint8)
    doc = np.repeat(np.arange(n), np.diff(offsets))
    out[np.arange(len(raw)) + 2 * doc] = raw
    space = _IS_SPACE[out]
    out[space] = 0x20
    ends = offsets[1:] + 2 * np.arange(1, n + 1) - 1
    out[ends] = 0x0A
    space[ends] = False
    before = np.empty(len(out), bool)
    if len(out):
        before[0] = True
        before[1:] = space[:-1]
        before[ends[:-1] + 1] = True  # a text starts as after a space
    kept = out[~(space & before)]
    return _LOWER[kept] if lower else kept


def segments(stream: np.ndarray) -> tuple[pa.Array, np.ndarray]:
    """The words of a word_stream with their closing byte (0x0A alone: the end of a text), and whether each is an end."""
    cut = np.flatnonzero((stream == 0x20) | (stream == 0x0A)) + 1
    offsets = np.concatenate([[0], cut]).astype(np.int64)
    array = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(cut), [None, pa.py_buffer(offsets), pa.py_buffer(np.ascontiguousarray(stream))])
    return array, stream[cut - 1] == 0x0A


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words whose every output bit depends on every input bit (the finaliser of splitmix64)."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x
