"""Media columns of telephony audio.

A payload is stored as 8-bit companded samples in a RIFF/WAVE file (mu-law by
default), which loses nothing: one byte is one sample.  Reading expands mu-law
and A-law through lookup tables, or decodes 4-bit ADPCM blocks with numpy
across all blocks of a batch at once, and gives 16-bit PCM that is resampled
and stored as a WAVE file of its own.

All features are sums of integers over one document's own samples, so equal
texts have equal values however rows are batched.  Null text counts as empty
and becomes one frame of padding; very long texts are decoded and resampled some
samples at a time.  Rows are mapped one by one; repeated rows
and other columns have no effect and an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_mapped, map_rows

FRAME = 192
TAIL = 16
RATE = 8000
PCM_TAG, ADPCM_TAG, ALAW_TAG, MULAW_TAG = 1, 0x11, 6, 7

#: Fixed values of the 4-bit ADPCM format: how a code moves the step index.
INDEX_MOVES = np.array([-1, -1, -1, -1, 2, 4, 6, 8] * 2, dtype=np.int32)

#: Fixed values of the 4-bit ADPCM format: the 89 step sizes.
STEPS = np.array([
    7, 8, 9, 10, 11, 12, 13, 14, 16, 17, 19, 21, 23, 25, 28, 31, 34, 37, 41, 45, 50, 55, 60, 66, 73, 80, 88,
    97, 107, 118, 130, 143, 157, 173, 190, 209, 230, 253, 279, 307, 337, 371, 408, 449, 494, 544, 598, 658,
    724, 796, 876, 963, 1060, 1166, 1282, 1411, 1552, 1707, 1878, 2066, 2272, 2499, 2749, 3024, 3327, 3660,
    4026, 4428, 4871, 5358, 5894, 6484, 7132, 7845, 8630, 9493, 10442, 11487, 12635, 13899, 15289, 16818,
    18500, 20350, 22385, 24623, 27086, 29794, 32767,
], dtype=np.int32)


def mulaw_table() -> np.ndarray:
    """Linear values of the 256 mu-law codes."""
    code = ~np.arange(256, dtype=np.int32) & 0xFF
    size = ((((code & 0x0F) << 3) + 0x84) << ((code & 0x70) >> 4)) - 0x84
    return np.where(code & 0x80, -size, size).astype(np.int16)


def alaw_table() -> np.ndarray:
    """Linear values of the 256 A-law codes."""
    code = np.arange(256, dtype=np.int32) ^ 0x55
    segment, size = (code & 0x70) >> 4, (code & 0x0F) << 4
    size = np.where(segment == 0, size + 8, (size + 0x108) << np.maximum(segment - 1, 0))
    return np.where(code & 0x80, size, -size).astype(np.int16)


MULAW, ALAW = mulaw_table(), alaw_table()


def nearest_codes(samples: np.ndarray, table: np.ndarray) -> bytes:
    """The 8-bit codes whose linear values lie nearest to PCM samples."""
    order = np.argsort(table, kind="stable")
    values = table[order].astype(np.int32)
    edges = (values[1:] + values[:-1] + 1) // 2
    return order[np.searchsorted(edges, samples.astype(np.int32), side="right")].astype(np.uint8).tobytes()


def decode_adpcm(blocks: np.ndarray) -> np.ndarray:
    """PCM of (blocks, bytes) ADPCM blocks, all blocks side by side.

    A block starts with its first sample (16 bits), the step index and a spare
    byte; each further byte holds two codes, the low one first.
    """
    count, width = blocks.shape
    codes = np.empty((2 * (width - 4), count), dtype=np.uint8)
    body = blocks[:, 4:].T
    codes[0::2], codes[1::2] = body & 15, body >> 4
    value = (blocks[:, 0].astype(np.int32) | blocks[:, 1].astype(np.int32) << 8).astype(np.int16).astype(np.int32)
    index = np.minimum(blocks[:, 2], 88).astype(np.int32)
    out = np.empty((len(codes) + 1, count), dtype=np.int16)
    out[0] = value
    for k, code in enumerate(codes):
        step = STEPS[index]
        move = step >> 3
        move += (step >> 2) * (code & 1)
        move += (step >> 1) * (code >> 1 & 1)
        move += step * (code >> 2 & 1)
        value += np.where(code & 8, -move, move)
        np.clip(value, -32768, 32767, out=value)
        index += INDEX_MOVES[code]
        np.clip(index, 0, 88, out=index)
        out[k + 1] = value
    return np.ascontiguousarray(out.T)


def encode_adpcm(samples: np.ndarray, width: int = FRAME) -> np.ndarray:
    """ADPCM blocks of (blocks, 2 * (width - 4) + 1) PCM samples."""
    count, length = samples.shape
    value, index = samples[:, 0].astype(np.int32), np.zeros(count, dtype=np.int32)
    codes = np.zeros((length - 1, count), dtype=np.uint8)
    blocks = np.zeros((count, width), dtype=np.uint8)
    blocks[:, 0], blocks[:, 1] = value & 0xFF, value >> 8 & 0xFF
    for k in range(1, length):
        step = STEPS[index]
        gap = samples[:, k].astype(np.int32) - value
        code = np.where(gap < 0, 8, 0)
        rest, move = np.abs(gap), step >> 3
        for bit, part in ((4, step), (2, step >> 1), (1, step >> 2)):
            on = rest >= part
            code, rest, move = code + bit * on, rest - part * on, move + part * on
        value = np.clip(value + np.where(code & 8, -move, move), -32768, 32767)
        index = np.clip(index + INDEX_MOVES[code], 0, 88)
        codes[k - 1] = code
    blocks[:, 4:] = (codes[0::2] | codes[1::2] << 4).T
    return blocks


#: Samples that are resampled at once: bounds the memory of one pass.
SAMPLES = 1 << 18


def resample(samples: np.ndarray, up: int = 2, down: int = 1) -> np.ndarray:
    """Linear resampling by up/down in integers, some samples at a time."""
    count = (len(samples) * up + down - 1) // down
    out = np.empty(count, dtype=np.int16)
    for begin in range(0, count, SAMPLES):
        at = np.arange(begin, min(count, begin + SAMPLES), dtype=np.int64) * down
        left, part = at // up, (at % up).astype(np.int32)
        here = samples[left].astype(np.int32)
        there = samples[np.minimum(left + 1, len(samples) - 1)].astype(np.int32)
        out[begin : begin + SAMPLES] = (here * (up - part) + there * part) // up
    return out


def square_sum(samples: np.ndarray) -> int:
    """Sum of squares, some samples at a time."""
    total = 0
    for begin in range(0, len(samples), SAMPLES):
        x = samples[begin : begin + SAMPLES].astype(np.int64)
        total += int(np.dot(x, x))
    return total


def write_wave(payload: bytes, tag: int = MULAW_TAG, rate: int = RATE) -> bytes:
    """A WAVE file; chunks are padded to even lengths."""
    bits, align = {PCM_TAG: (16, 2), ADPCM_TAG: (4, FRAME)}.get(tag, (8, 1))
    unit = 2 * (FRAME - 4) + 1 if tag == ADPCM_TAG else 1
    speed = rate * align // unit
    extra = b"" if tag == PCM_TAG else struct.pack("<HH", 2, unit) if tag == ADPCM_TAG else struct.pack("<H", 0)
    form = struct.pack("<HHIIHH", tag, 1, rate, speed, align, bits) + extra
    fact = b"" if tag == PCM_TAG else b"fact" + struct.pack("<II", 4, len(payload) // align * unit)
    data = b"data" + struct.pack("<I", len(payload)) + payload + b"\0" * (len(payload) & 1)
    body = b"WAVEfmt " + struct.pack("<I", len(form)) + form + fact + data
    return b"RIFF" + struct.pack("<I", len(body)) + body


def read_wave(stored: bytes) -> tuple[int, int, bytes]:
    """Format tag, rate and sample bytes of a WAVE file, chunk by chunk."""
    if stored[:4] != b"RIFF" or stored[8:12] != b"WAVE":
        raise ValueError("not a WAVE file")
    at, tag, rate = 12, 0, 0
    while at + 8 <= len(stored):
        name, size = stored[at : at + 4], struct.unpack_from("<I", stored, at + 4)[0]
        if name == b"fmt ":
            tag, _, rate = struct.unpack_from("<HHI", stored, at + 8)
        elif name == b"data":
            return tag, rate, stored[at + 8 : at + 8 + size]
        at += 8 + size + (size & 1)
    raise ValueError("no samples in the file")


def to_pcm(stored: bytes) -> tuple[int, np.ndarray]:
    """Rate and 16-bit samples of a stored file of any of the formats."""
    tag, rate, payload = read_wave(stored)
    codes = np.frombuffer(payload, dtype=np.uint8)
    if tag == MULAW_TAG:
        return rate, MULAW[codes]
    if tag == ALAW_TAG:
        return rate, ALAW[codes]
    if tag == ADPCM_TAG:
        return rate, decode_adpcm(codes.reshape(-1, FRAME)).ravel()
    return rate, np.frombuffer(payload, dtype="<i2")


def padded(text: str | None) -> tuple[bytes, int]:
    """UTF-8 bytes filled with spaces to a positive multiple of the frame."""
    raw = (text or "").encode()
    return raw.ljust(max(1, -(-len(raw) // FRAME)) * FRAME, b" "), len(raw)


def store_audio(docs: DataFrame, tag: int = MULAW_TAG, up: int = 2, down: int = 1) -> DataFrame:
    """doc_id, n_bytes, ``media`` (the stored payload) and ``pcm`` (a WAVE file
    of the decoded, resampled samples)."""

    def kernel(batch: pa.RecordBatch) -> dict:
        media, pcm, sizes = [], [], []
        for value in batch.column(1):
            payload, size = padded(value.as_py())
            media.append(write_wave(payload, tag))
            rate, samples = to_pcm(media[-1])
            pcm.append(write_wave(resample(samples, up, down).astype("<i2").tobytes(), PCM_TAG, rate * up // down))
            sizes.append(size)
        return {"doc_id": batch.column(0), "n_bytes": sizes, "media": media, "pcm": pcm}

    return map_rows(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), kernel, "doc_id long, n_bytes long, media binary, pcm binary")


def load_payload(media: DataFrame) -> DataFrame:
    """doc_id and the payload bytes read back from ``media``."""
    kernel = lambda b: {"doc_id": b.column(0), "payload": [read_wave(x.as_py())[2] for x in b.column(1)]}
    return map_rows(media.select("doc_id", "media"), kernel, "doc_id long, payload binary")


#: Blocks that are decoded side by side: bounds the memory of one pass.
BLOCKS = 4096


def audio_report(docs: DataFrame) -> DataFrame:
    """Reads the media and PCM columns of ``store_audio`` back and measures them.

    ``feature`` holds integers, comma-joined: mean square of the mu-law and of
    the A-law reading, zero crossings of the mu-law reading, mean square of the
    ADPCM reading of the same bytes, crc32 of the stored PCM's samples.
    """

    def kernel(batch: pa.RecordBatch) -> dict:
        out: dict[str, list] = {k: [] for k in ("n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature")}
        found, energies = [], []
        waiting: list[np.ndarray] = []
        blocks: list[int] = []

        def decode() -> None:
            if waiting:
                pcm = decode_adpcm(np.concatenate(waiting)).astype(np.int64)
                rows = np.einsum("ij,ij->i", pcm, pcm)
                energies.append(rows)
                waiting.clear()

        size = 0
        for n, media, pcm in zip(batch.column(1).to_pylist(), batch.column(2), batch.column(3)):
            media = media.as_py()
            _, _, back = read_wave(media)
            codes = np.frombuffer(back, dtype=np.uint8)
            mu, a = MULAW[codes], ALAW[codes]
            squares = [square_sum(y) // len(y) for y in (mu, a)]
            crossings = int(((mu[1:] < 0) != (mu[:-1] < 0)).sum())
            wide = zlib.crc32(read_wave(pcm.as_py())[2])
            found.append((*squares, crossings, wide))
            grid = codes.reshape(-1, FRAME)
            blocks.append(len(grid))
            for at in range(0, len(grid), BLOCKS):
                waiting.append(grid[at : at + BLOCKS])
                size += len(waiting[-1])
                if size >= BLOCKS:
                    decode()
                    size = 0
            out["n_bytes"].append(n)
            out["payload_bytes"].append(len(back))
            out["payload_sha256"].append(hashlib.sha256(back).hexdigest())
            out["tail_crc32"].append(zlib.crc32(back[-TAIL:]))
            out["media_bytes"].append(len(media))
            out["media_sha256"].append(hashlib.sha256(media).hexdigest())
        decode()
        if blocks:
            first = np.concatenate([[0], np.cumsum(blocks)[:-1]])
            sums = np.add.reduceat(np.concatenate(energies), first)
            per = 2 * (FRAME - 4) + 1
            out["feature"] = [f"{m},{a},{z},{int(s) // (b * per)},{w}" for (m, a, z, w), s, b in zip(found, sums, blocks)]
        return {"doc_id": batch.column(0), **out}

    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
    return map_mapped(store_audio(docs), kernel, schema)
