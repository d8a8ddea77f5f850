"""Telephony audio columns: mu-law and A-law expanded by lookup tables, ADPCM blocks decoded with numpy across
blocks, PCM resampled; payloads stored losslessly as 8-bit telephony samples in a WAV container."""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, materialize, pick, slices, utf8_buffer

MU_LAW, A_LAW, ADPCM = "mulaw", "alaw", "adpcm"
#: Fixed values of the WAV format: the format tag of each codec.
FORMAT_TAGS = {A_LAW: 6, MU_LAW: 7, ADPCM: 0x11}
#: Fixed values of IMA ADPCM: how each 4-bit code moves the step index (by its three magnitude bits).
INDEX_SHIFT = np.array([-1, -1, -1, -1, 2, 4, 6, 8], np.int32)
#: An ADPCM block: a 4-byte header (first sample, step index, 0) and 60 bytes of two codes each.
BLOCK = 64
UNIT = 64
#: Parts in which a table's media are written and decoded.
STORED_PARTS = 3
#: Bytes of payload decoded at once: bounds the memory of a worker.
SLICE = 2 << 20


def step_sizes() -> np.ndarray:
    """The 89 IMA step sizes, each about a tenth above the one before."""
    # Fixed values of IMA ADPCM, in their published order.
    return np.array([7, 8, 9, 10, 11, 12, 13, 14, 16, 17, 19, 21, 23, 25, 28, 31, 34, 37, 41, 45, 50, 55, 60, 66, 73, 80, 88, 97, 107, 118, 130, 143, 157, 173, 190, 209, 230, 253, 279, 307, 337, 371, 408, 449, 494, 544, 598, 658, 724, 796, 876, 963, 1060, 1166, 1282, 1411, 1552, 1707, 1878, 2066, 2272, 2499, 2749, 3024, 3327, 3660, 4026, 4428, 4871, 5358, 5894, 6484, 7132, 7845, 8630, 9493, 10442, 11487, 12635, 13899, 15289, 16818, 18500, 20350, 22385, 24623, 27086, 29794, 32767], np.int32)


def mu_law_table() -> np.ndarray:
    """G.711 mu-law codes to 16-bit PCM: bits inverted; sign, 3-bit exponent, 4-bit mantissa, bias 0x84."""
    code = ~np.arange(256) & 0xFF
    size = (((code & 0x0F) << 3) + 0x84 << ((code >> 4) & 7)) - 0x84
    return np.where(code & 0x80, -size, size).astype(np.int16)


def a_law_table() -> np.ndarray:
    """G.711 A-law codes to 16-bit PCM: even bits inverted; exponent 0 is linear."""
    code = np.arange(256) ^ 0x55
    exponent, mantissa = (code >> 4) & 7, (code & 0x0F) << 4
    size = np.where(exponent == 0, mantissa + 8, (mantissa + 0x108) << np.maximum(exponent - 1, 0))
    return np.where(code & 0x80, size, -size).astype(np.int16)


MU_LAW_PCM, A_LAW_PCM, STEPS = mu_law_table(), a_law_table(), step_sizes()


def adpcm_moves() -> tuple[np.ndarray, np.ndarray]:
    """For each (step index, code): the change of the sample, and the next step index."""
    step, code = STEPS[:, None], np.arange(16)[None, :]
    change = (step >> 3) + np.where(code & 1, step >> 2, 0) + np.where(code & 2, step >> 1, 0) + np.where(code & 4, step, 0)
    after = np.clip(np.arange(len(STEPS))[:, None] + INDEX_SHIFT[code & 7], 0, len(STEPS) - 1)
    return np.where(code & 8, -change, change).astype(np.int32).ravel(), after.astype(np.int32).ravel()


_CHANGE, _AFTER = adpcm_moves()


def decode_adpcm(blocks: np.ndarray) -> np.ndarray:
    """uint8 (n, bytes) IMA blocks -> int16 (n, 1 + 2 * (bytes - 4)): one numpy step a code for all blocks at once."""
    n, width = blocks.shape
    head = blocks[:, :2].astype(np.int32)
    sample = (head[:, 0] | head[:, 1] << 8).astype(np.uint16).view(np.int16).astype(np.int32)
    index = np.minimum(blocks[:, 2].astype(np.int32), len(STEPS) - 1)
    out = np.empty((1 + 2 * (width - 4), n), np.int16)
    out[0] = sample
    codes = np.ascontiguousarray(blocks[:, 4:].T)
    row = 1
    for byte in codes:
        for code in (byte & 0x0F, byte >> 4):
            at = (index << 4) + code
            sample = np.clip(sample + _CHANGE[at], -32768, 32767)
            index = _AFTER[at]
            out[row] = sample
            row += 1
    return out.T


def adpcm_from_payload(payload: np.ndarray) -> np.ndarray:
    """Bytes (a multiple of 60, or padded by 0) as the codes of blocks whose headers are 0."""
    body = BLOCK - 4
    n = -(-len(payload) // body)
    blocks = np.zeros((n, BLOCK), np.uint8)
    padded = np.zeros(n * body, np.uint8)
    padded[: len(payload)] = payload
    blocks[:, 4:] = padded.reshape(n, body)
    return blocks


def payload_from_adpcm(blocks: np.ndarray, n_bytes: int) -> np.ndarray:
    return blocks[:, 4:].reshape(-1)[:n_bytes]


def expand(codec: str, data: np.ndarray) -> np.ndarray:
    """Stored samples -> int16 PCM."""
    if codec == MU_LAW:
        return MU_LAW_PCM[data]
    if codec == A_LAW:
        return A_LAW_PCM[data]
    if codec == ADPCM:
        return decode_adpcm(data.reshape(-1, BLOCK)).reshape(-1)
    raise ValueError(f"unknown codec {codec}")


def resample(pcm: np.ndarray, up: int = 1, down: int = 1) -> np.ndarray:
    """`up` / `down` times the rate, in whole numbers: linear interpolation (the last sample is held), then means of
    `down` samples each (the last one of what is left)."""
    wide = pcm.astype(np.int32)
    if up > 1:
        following = np.append(wide[1:], wide[-1:])
        wide = np.stack([(wide * (up - k) + following * k) // up for k in range(up)], 1).reshape(-1)
    if down > 1 and len(wide):
        starts = np.arange(0, len(wide), down)
        wide = np.add.reduceat(wide, starts) // np.diff(np.append(starts, len(wide)))
    return wide.astype(np.int16)


def wav_file(codec: str, data: bytes, rate: int = 8000) -> bytes:
    """A mono WAV file of the given codec."""
    if codec == ADPCM:
        per_block = 1 + 2 * (BLOCK - 4)
        form = struct.pack("<HHIIHHHH", FORMAT_TAGS[codec], 1, rate, rate * BLOCK // per_block, BLOCK, 4, 2, per_block)
    else:
        form = struct.pack("<HHIIHHH", FORMAT_TAGS[codec], 1, rate, rate, 1, 8, 0)
    pad = b"\0" * (len(data) & 1)
    chunks = b"fmt " + struct.pack("<I", len(form)) + form + b"data" + struct.pack("<I", len(data)) + data + pad
    return b"RIFF" + struct.pack("<I", 4 + len(chunks)) + b"WAVE" + chunks


def read_wav(stored: bytes) -> tuple[str, int, bytes]:
    """codec, rate and sample data of a WAV file made by wav_file or any other RIFF writer."""
    if stored[:4] != b"RIFF" or stored[8:12] != b"WAVE":
        raise ValueError("not a WAV file")
    at, codec, rate = 12, None, 0
    while at + 8 <= len(stored):
        kind, size = stored[at : at + 4], struct.unpack_from("<I", stored, at + 4)[0]
        if kind == b"fmt ":
            tag, _, rate = struct.unpack_from("<HHI", stored, at + 8)
            codec = {v: k for k, v in FORMAT_TAGS.items()}.get(tag)
        elif kind == b"data":
            if codec is None:
                raise ValueError("format of the samples unknown")
            return codec, rate, stored[at + 8 : at + 8 + size]
        at += 8 + size + (size & 1)
    raise ValueError("no sample data")


def pad_payload(raw: bytes) -> bytes:
    """Zero bytes up to a positive multiple of UNIT."""
    return raw + bytes(-len(raw) % UNIT or (0 if raw else UNIT))


def features(pcm: np.ndarray, codec: str) -> str:
    """codec, samples, peak, mean absolute sample, zero crossings and CRC-32 of PCM, in whole numbers."""
    wide = pcm.astype(np.int32)
    size = np.abs(wide)
    crossings = int(np.count_nonzero((wide[1:] < 0) != (wide[:-1] < 0)))
    return f"{codec}:{len(pcm)}:{int(size.max(initial=0))}:{int(size.sum(dtype=np.int64)) // max(1, len(pcm))}:{crossings}:{zlib.crc32(pcm.astype('<i2').tobytes()) & 0xFFFFFFFF:08x}"


def codec_of(payload: bytes) -> str:
    """Each codec takes a third of all payloads, by their hash: equal payloads take the same."""
    return (MU_LAW, A_LAW, ADPCM)[zlib.crc32(payload) % 3]


def store_media(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", codec: str | None = None) -> DataFrame:
    """docs -> (doc_id, n_bytes, payload_bytes, media): each text's padded UTF-8 bytes as samples of a WAV file of a codec,
    or of the one that codec_of() gives it.

    Lossless: the bytes are the stored codes. Null is the empty text (64 zero bytes). One output row an input row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text", SLICE):
            raw, at = utf8_buffer(batch.column(1))
            media, padded_bytes = [], []
            for i in range(len(at) - 1):
                payload = pad_payload(raw[at[i] : at[i + 1]].tobytes())
                padded_bytes.append(len(payload))
                own = codec or codec_of(payload)
                media.append(wav_file(own, adpcm_from_payload(np.frombuffer(payload, np.uint8)).tobytes() if own == ADPCM else payload))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.diff(at)), pa.array(padded_bytes, pa.int64()), pa.array(media, pa.binary())], names=["doc_id", "n_bytes", "payload_bytes", "media"])

    chosen = pick(docs, doc_id=id_col, text=text_col)
    return chosen.mapInArrow(run, f"doc_id {chosen.schema['doc_id'].dataType.simpleString()}, n_bytes long, payload_bytes long, media binary")


def decoded(files: list[bytes]) -> list[tuple[str, int, bytes, np.ndarray]]:
    """(codec, rate, sample data, PCM) of each file; all ADPCM blocks of the list are decoded together."""
    read = [read_wav(f) for f in files]
    blocks = [np.frombuffer(data, np.uint8).reshape(-1, BLOCK) for codec, _, data in read if codec == ADPCM]
    codes = decode_adpcm(np.concatenate(blocks)) if blocks else None
    out, start = [], 0
    for codec, rate, data in read:
        if codec == ADPCM:
            n = len(data) // BLOCK
            out.append((codec, rate, data, codes[start : start + n].reshape(-1)))
            start += n
        else:
            out.append((codec, rate, data, expand(codec, np.frombuffer(data, np.uint8))))
    return out


def resampled_media(media: DataFrame, up: int = 1, down: int = 2) -> DataFrame:
    """(doc_id, n_bytes, payload_bytes, media) -> (doc_id, n_bytes, payload_bytes, payload_sha256, tail_crc32, media_bytes,
    media_sha256, codec, rate, pcm): digests of what is read back from the stored files, and their PCM, little-endian and 16
    bits wide, at `up` / `down` times the stored rate."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "media", SLICE):
            files, sizes = batch.column(3).to_pylist(), batch.column(2).to_pylist()
            read = decoded(files)
            payloads = [payload_from_adpcm(np.frombuffer(data, np.uint8).reshape(-1, BLOCK), n).tobytes() if codec == ADPCM else data[:n] for (codec, _, data, _), n in zip(read, sizes, strict=True)]
            pcm = [resample(samples, up, down).astype("<i2").tobytes() for *_, samples in read]
            columns = [*batch.columns[:3], pa.array([hashlib.sha256(p).hexdigest() for p in payloads], pa.string()), pa.array([zlib.crc32(p[-UNIT:]) & 0xFFFFFFFF for p in payloads], pa.int64()), pa.array([len(f) for f in files], pa.int64()), pa.array([hashlib.sha256(f).hexdigest() for f in files], pa.string()), pa.array([c for c, *_ in read], pa.string()), pa.array([rate * up // down for _, rate, *_ in read], pa.int32()), pa.array(pcm, pa.binary())]
            yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "codec", "rate", "pcm"])

    kind = media.schema["doc_id"].dataType.simpleString()
    return media.select("doc_id", "n_bytes", "payload_bytes", "media").mapInArrow(run, f"doc_id {kind}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, codec string, rate int, pcm binary")


def media_digests(resampled: DataFrame) -> DataFrame:
    """resampled_media() -> the same with `feature`, of the PCM read back, in place of codec, rate and pcm."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "pcm", SLICE):
            said = [features(np.frombuffer(pcm, "<i2"), f"{codec}@{rate}") for codec, rate, pcm in zip(*(batch.column(i).to_pylist() for i in (7, 8, 9)), strict=True)]
            yield pa.RecordBatch.from_arrays([*batch.columns[:7], pa.array(said, pa.string())], names=[*batch.schema.names[:7], "feature"])

    kind = resampled.schema["doc_id"].dataType.simpleString()
    return resampled.mapInArrow(run, f"doc_id {kind}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")


def stored_digests(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", codec: str | None = None, parts: int = STORED_PARTS) -> DataFrame:
    """The whole way: media files are written as a column of a table, read, decoded; their resampled PCM is written as a
    column of another, and read for the features. All tables are in the shared folder. It is gone in `parts`, rows dealt by
    a hash of id and text: the media of a part go when its PCM is written, which bounds the room that both take."""
    chosen = pick(docs, doc_id=id_col, text=text_col)
    held = []
    for part in range(parts):
        media = materialize(store_media(chosen.where(F.pmod(F.xxhash64("doc_id", "text"), F.lit(parts)) == part), codec=codec), "media", "zstd")
        held.append(materialize(resampled_media(media), "media-pcm", "zstd"))
        discard(media)
    return media_digests(reduce(DataFrame.unionByName, held))
