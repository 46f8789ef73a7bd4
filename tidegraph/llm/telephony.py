"""Telephony audio columns: mu-law and A-law by lookup table, ADPCM across blocks, resampled PCM."""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from tidegraph.runtime import ship

FRAME = 576
RATE = 8000
#: Format tags of the container.
PCM, ALAW, MULAW, ADPCM = 1, 6, 7, 0x11
#: Blocks decoded together; bounds the memory of a task whatever the batch.
TOGETHER = 8192


def mulaw_table() -> np.ndarray:
    """16-bit sample of each mu-law code."""
    code = ~np.arange(256) & 0xFF
    size = ((((code & 15) << 3) + 132) << ((code >> 4) & 7)) - 132
    return np.where(code & 0x80, -size, size).astype(np.int16)


def alaw_table() -> np.ndarray:
    """16-bit sample of each A-law code."""
    code = np.arange(256) ^ 0x55
    part, size = (code >> 4) & 7, ((code & 15) << 4) + 8
    size = np.where(part > 0, (size + 256) << np.maximum(part - 1, 0), size)
    return np.where(code & 0x80, size, -size).astype(np.int16)


def adpcm_steps() -> np.ndarray:
    """The 89 quantiser steps."""
    # Fixed values of the format.
    return np.array(
        [7, 8, 9, 10, 11, 12, 13, 14, 16, 17, 19, 21, 23, 25, 28, 31, 34, 37, 41, 45, 50, 55, 60, 66, 73, 80, 88, 97, 107, 118, 130, 143, 157, 173, 190, 209, 230, 253, 279, 307, 337, 371, 408, 449, 494, 544, 598, 658, 724, 796, 876, 963, 1060, 1166, 1282, 1411, 1552, 1707, 1878, 2066, 2272, 2499, 2749, 3024, 3327, 3660, 4026, 4428, 4871, 5358, 5894, 6484, 7132, 7845, 8630, 9493, 10442, 11487, 12635, 13899, 15289, 16818, 18500, 20350, 22385, 24623, 27086, 29794, 32767],
        dtype=np.int32,
    )


# Fixed values of the format: how a nibble's size moves the step.
_MOVES = np.array([-1, -1, -1, -1, 2, 4, 6, 8], dtype=np.int32)
_MULAW, _ALAW, _STEPS = mulaw_table(), alaw_table(), adpcm_steps()


def _adpcm_differences() -> tuple[np.ndarray, np.ndarray]:
    """(difference, next step) by step and nibble."""
    step, nibble = _STEPS[:, None], np.arange(16)[None, :]
    size = (step >> 3) + np.where(nibble & 4, step, 0) + np.where(nibble & 2, step >> 1, 0) + np.where(nibble & 1, step >> 2, 0)
    after = np.clip(np.arange(89)[:, None] + _MOVES[nibble & 7], 0, 88)
    return np.where(nibble & 8, -size, size).astype(np.int32).ravel(), after.astype(np.int32).ravel()


_DIFFERENCE, _AFTER = _adpcm_differences()


def decode_adpcm(blocks: np.ndarray) -> np.ndarray:
    """(blocks, bytes) of mono 4-bit ADPCM blocks -> (blocks, samples) 16-bit. All blocks advance together, sample by sample."""
    head = blocks[:, :2].copy().view("<i2").astype(np.int32).ravel()
    index = np.minimum(blocks[:, 2].astype(np.int32), 88)
    body = np.ascontiguousarray(blocks[:, 4:].T)
    out = np.empty((1 + 2 * body.shape[0], blocks.shape[0]), dtype=np.int16)
    out[0] = head
    at = 1
    for row in body:
        for nibble in (row & 15, row >> 4):
            cell = (index << 4) + nibble
            head = np.clip(head + _DIFFERENCE[cell], -32768, 32767)
            index = _AFTER[cell]
            out[at] = head
            at += 1
    return out.T


def resample_double(x: np.ndarray) -> np.ndarray:
    """Twice the rate: samples stay, half-way ones come from four neighbours with weights -1, 9, 9, -1 of 16, in integers."""
    if not len(x):
        return x.astype(np.int16)
    wide = np.pad(x.astype(np.int32), (1, 2), mode="edge")
    between = (9 * (wide[1:-2] + wide[2:-1]) - wide[:-3] - wide[3:] + 8) >> 4
    out = np.empty(2 * len(x), dtype=np.int16)
    out[::2], out[1::2] = x, np.clip(between, -32768, 32767)
    return out


def container(tag: int, rate: int, bits: int, align: int, data: bytes) -> bytes:
    """A mono WAV file."""
    extra = struct.pack("<HH", 2, (align - 4) * 2 + 1) if tag == ADPCM else b"" if tag == PCM else struct.pack("<H", 0)
    form = struct.pack("<HHIIHH", tag, 1, rate, rate * bits // 8, align, bits) + extra
    body = b"WAVE" + b"fmt " + struct.pack("<I", len(form)) + form + b"data" + struct.pack("<I", len(data)) + data + b"\0" * (len(data) & 1)
    return b"RIFF" + struct.pack("<I", len(body)) + body


def parts(media: bytes) -> tuple[int, int, int, bytes]:
    """(format tag, rate, block align, data) of a WAV file; a ValueError if it is none."""
    if len(media) < 12 or media[:4] != b"RIFF" or media[8:12] != b"WAVE":
        raise ValueError("not a WAV file")
    at, form = 12, None
    while at + 8 <= len(media):
        name, size = media[at : at + 4], struct.unpack_from("<I", media, at + 4)[0]
        if name == b"fmt ":
            form = struct.unpack_from("<HHIIHH", media, at + 8)
        elif name == b"data":
            if form is None:
                raise ValueError("data before format")
            return form[0], form[2], form[4], media[at + 8 : at + 8 + size]
        at += 8 + size + (size & 1)
    raise ValueError("no data")


def decode(media: bytes) -> tuple[int, np.ndarray]:
    """(rate, 16-bit samples) of a mono WAV file in mu-law, A-law, ADPCM or 16-bit PCM."""
    tag, rate, align, data = parts(media)
    if tag == MULAW:
        return rate, _MULAW[np.frombuffer(data, np.uint8)]
    if tag == ALAW:
        return rate, _ALAW[np.frombuffer(data, np.uint8)]
    if tag == PCM:
        return rate, np.frombuffer(data[: len(data) & ~1], "<i2")
    if tag == ADPCM:
        whole = len(data) // align
        return rate, decode_adpcm(np.frombuffer(data[: whole * align], np.uint8).reshape(whole, align)).ravel() if whole else np.zeros(0, np.int16)
    raise ValueError(f"format {tag} isn't known")


def decode_column(df: DataFrame, media_col: str = "media", out_col: str = "pcm") -> DataFrame:
    """Adds ``out_col``: the media's samples at twice their rate as a 16-bit PCM WAV file; null where the media is null or no known WAV."""
    ship(df.sparkSession)

    @F.pandas_udf("binary")
    def run(media):
        def one(x):
            if x is None:
                return None
            try:
                rate, samples = decode(bytes(x))
            except (ValueError, struct.error):
                return None
            return container(PCM, 2 * rate, 16, 2, resample_double(samples).tobytes())

        return media.map(one)

    return df.withColumn(out_col, run(media_col))


def _figures(samples: np.ndarray) -> str:
    """Root mean square, zero crossings and peak, as integers."""
    wide = samples.astype(np.int64)
    negative = samples < 0
    return f"{int(np.sqrt(int((wide * wide).sum()) // len(wide)))},{int(np.count_nonzero(negative[1:] != negative[:-1]))},{int(np.abs(wide).max())}"


def store_texts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Texts as the payload of mu-law media, read back, decoded and measured.

    ``doc_id, n_bytes, payload_bytes, payload_sha256, tail_crc32, media_bytes, media_sha256, feature``. The payload is the
    UTF-8 text padded with bytes 255 to a positive multiple of 576; null counts as empty. ``feature`` holds, of the bytes
    read back: the figures as mu-law and as A-law samples, those as ADPCM blocks of 576 bytes (decoded across the blocks of
    many texts at once), and length and CRC of the mu-law samples resampled to 16 kHz and stored as PCM.
    """
    ship(docs.sparkSession)
    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
    names = [x.split()[0] for x in schema.split(", ")]

    def run(batches):
        for batch in batches:
            ids, texts = batch.column(0).to_pylist(), batch.column(1).cast(pa.binary()).to_pylist()
            rows, at = [], 0
            while at < len(ids):
                group, blocks = [], 0
                while at < len(ids) and (not group or blocks < TOGETHER):
                    raw = texts[at] or b""
                    media = container(MULAW, RATE, 8, 1, raw + b"\xff" * (max(1, -(-len(raw) // FRAME)) * FRAME - len(raw)))
                    data = parts(media)[3]
                    group.append((ids[at], len(raw), media, data))
                    blocks += len(data) // FRAME
                    at += 1
                joined = np.frombuffer(b"".join(x[3] for x in group), np.uint8).reshape(-1, FRAME)
                step = [joined[i : i + TOGETHER] for i in range(0, len(joined), TOGETHER)]
                samples = np.concatenate([decode_adpcm(x) for x in step])
                first = 0
                for doc, n, media, data in group:
                    codes, count = np.frombuffer(data, np.uint8), len(data) // FRAME
                    linear = _MULAW[codes]
                    pcm = container(PCM, 2 * RATE, 16, 2, resample_double(linear).tobytes())
                    feature = f"mulaw={_figures(linear)};alaw={_figures(_ALAW[codes])};adpcm={_figures(samples[first : first + count].ravel())};pcm={len(pcm)},{zlib.crc32(pcm):08x}"
                    first += count
                    rows.append((doc, n, len(data), hashlib.sha256(data).hexdigest(), zlib.crc32(data[-32:]), len(media), hashlib.sha256(media).hexdigest(), feature))
            columns = list(zip(*rows)) if rows else [[] for _ in names]
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.string() if n in ("payload_sha256", "media_sha256", "feature") else pa.int64()) for n, c in zip(names, columns)], names)

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, schema)
