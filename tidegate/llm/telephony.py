"""Telephony audio columns: mu-law and A-law by lookup tables, IMA ADPCM blocks by numpy across blocks, resampled PCM.

Media are RIFF/WAVE bytes with 8-bit companded samples (format 6 or 7) or IMA ADPCM blocks (format 17). They are written to the
shared folder and read again; decoders read the headers' chunks, so the payload that features see is what was stored. ADPCM
blocks of all media of a batch are decoded at once, some megabytes at a time. pcm_table() and store_pcm() give 16-bit PCM at
twice the stored rate.

Defined results: null text is empty; an empty payload is padded like any other, so there always are samples; with no format
asked for, a payload's CRC-32 chooses one of the three, so equal texts have equal media; media that are null are null again,
and those that are not WAVE of a known format raise; repeated rows are media of their own; an empty table gives no rows; extra
columns are left out, whatever their names.
"""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tidegate.llm.common import arrow_function, as_bytes, give_back, stored

A_LAW, MU_LAW, IMA_ADPCM = 6, 7, 17
RATE, BLOCK = 8000, 192
ADPCM_BLOCK = 96  # bytes of an ADPCM block that stored_media writes; BLOCK is a multiple
STRETCH = 2_000_000  # payload bytes that are decoded at a time


def mu_law_table() -> np.ndarray:
    """16-bit sample of each mu-law code: inverted bits are a sign, three bits of exponent and four of mantissa."""
    code = ~np.arange(256, dtype=np.int32) & 0xFF
    size = ((((code & 15) << 3) + 132) << (code >> 4 & 7)) - 132
    return np.where(code & 128, -size, size).astype(np.int16)


def a_law_table() -> np.ndarray:
    """16-bit sample of each A-law code, whose even bits are inverted."""
    code = np.arange(256, dtype=np.int32) ^ 0x55
    exponent, size = code >> 4 & 7, (code & 15) << 4
    size = np.where(exponent == 0, size + 8, (size + 264) << np.maximum(exponent - 1, 0))
    return np.where(code & 128, size, -size).astype(np.int16)


MU_TABLE, A_TABLE = mu_law_table(), a_law_table()
#: fixed values of the IMA ADPCM format: how each code moves the step index
IMA_MOVE = np.array([-1, -1, -1, -1, 2, 4, 6, 8] * 2, np.int32)
#: fixed values of the IMA ADPCM format: quantiser steps
IMA_STEP = np.array(
    [7, 8, 9, 10, 11, 12, 13, 14, 16, 17, 19, 21, 23, 25, 28, 31, 34, 37, 41, 45, 50, 55, 60, 66, 73, 80, 88, 97, 107, 118, 130, 143, 157, 173, 190,
     209, 230, 253, 279, 307, 337, 371, 408, 449, 494, 544, 598, 658, 724, 796, 876, 963, 1060, 1166, 1282, 1411, 1552, 1707, 1878, 2066, 2272, 2499,
     2749, 3024, 3327, 3660, 4026, 4428, 4871, 5358, 5894, 6484, 7132, 7845, 8630, 9493, 10442, 11487, 12635, 13899, 15289, 16818, 18500, 20350, 22385,
     24623, 27086, 29794, 32767], np.int32)


def decode_adpcm(data: bytes, block: int) -> np.ndarray:
    """16-bit samples of mono IMA ADPCM blocks: each sample of all blocks at once, STRETCH bytes of them at a time."""
    n = len(data) // block
    if n > 1 and n * block > STRETCH:
        step = max(1, STRETCH // block) * block
        return np.concatenate([decode_adpcm(data[a : a + step], block) for a in range(0, n * block, step)])
    raw = np.frombuffer(data[: n * block], np.uint8).reshape(n, block)
    value = raw[:, :2].copy().view("<i2")[:, 0].astype(np.int32)
    index = np.minimum(raw[:, 2], 88).astype(np.int32)
    codes = np.empty((n, 2 * (block - 4)), np.int32)
    codes[:, 0::2], codes[:, 1::2] = raw[:, 4:] & 15, raw[:, 4:] >> 4
    out = np.empty((n, 1 + codes.shape[1]), np.int16)
    out[:, 0] = value
    for k in range(codes.shape[1]):
        code, step = codes[:, k], IMA_STEP[index]
        move = (step >> 3) + (code & 1) * (step >> 2) + (code >> 1 & 1) * (step >> 1) + (code >> 2 & 1) * step
        value = np.clip(np.where(code & 8, value - move, value + move), -32768, 32767)
        index = np.clip(index + IMA_MOVE[code], 0, 88)
        out[:, k + 1] = value
    return out.reshape(-1)


def wave(payload: bytes, form: int = MU_LAW, rate: int = RATE, block: int = 1) -> bytes:
    """WAVE bytes around a payload of 8-bit samples, or of ADPCM blocks."""
    adpcm = form == IMA_ADPCM
    per_block = 2 * (block - 4) + 1
    form_chunk = struct.pack("<HHIIHHH", form, 1, rate, rate * block // per_block if adpcm else rate, block, 4 if adpcm else 8, 2 if adpcm else 0)
    form_chunk += struct.pack("<H", per_block) if adpcm else b""
    samples = len(payload) // block * per_block if adpcm else len(payload)
    body = b"WAVE" + b"".join(k + struct.pack("<I", len(v)) + v + b"\0" * (len(v) & 1) for k, v in ((b"fmt ", form_chunk), (b"fact", struct.pack("<I", samples)), (b"data", payload)))
    return b"RIFF" + struct.pack("<I", len(body) & 0xFFFFFFFF) + body


def read_wave(media: bytes) -> tuple[int, int, int, bytes]:
    """Format, rate, block size and payload of WAVE bytes."""
    if media[:4] != b"RIFF" or media[8:12] != b"WAVE":
        raise ValueError("not a WAVE file")
    at, form = 12, None
    while at + 8 <= len(media):
        kind, n = media[at : at + 4], struct.unpack_from("<I", media, at + 4)[0]
        if kind == b"fmt ":
            form, _, rate, _, block = struct.unpack_from("<HHIIH", media, at + 8)
        elif kind == b"data":
            if form not in (A_LAW, MU_LAW, IMA_ADPCM):
                raise ValueError(f"WAVE format {form}")
            return form, rate, block, media[at + 8 : at + 8 + n]
        at += 8 + n + (n & 1)
    raise ValueError("no data chunk")


def pcm(form: int, block: int, payload: bytes) -> np.ndarray:
    if form == IMA_ADPCM:
        return decode_adpcm(payload, block)
    return (MU_TABLE if form == MU_LAW else A_TABLE)[np.frombuffer(payload, np.uint8)]


def decoded(media: list[bytes | None]):
    """(payload, 16-bit samples) of each of some media, in order; ADPCM blocks of one size are decoded across media."""
    at = 0
    while at < len(media):
        part, size = [], 0
        while at < len(media) and (not part or size < STRETCH):
            part.append(None if media[at] is None else read_wave(media[at]))
            size += len(media[at] or b"")
            at += 1
        samples: list = [None] * len(part)
        for block in {x[2] for x in part if x and x[0] == IMA_ADPCM}:
            rows = [k for k, x in enumerate(part) if x and x[0] == IMA_ADPCM and x[2] == block]
            n = [len(part[k][3]) // block for k in rows]
            whole = decode_adpcm(b"".join(part[k][3][: m * block] for k, m in zip(rows, n, strict=True)), block)
            cuts = np.cumsum(n)[:-1] * (2 * (block - 4) + 1)
            for k, x in zip(rows, np.split(whole, cuts), strict=True):
                samples[k] = x
        for x, found in zip(part, samples, strict=True):
            yield (None, None) if x is None else (x[3], pcm(x[0], x[2], x[3]) if found is None else found)


def doubled(samples: np.ndarray) -> np.ndarray:
    """Twice the rate: between two samples stands their mean (towards minus infinity), after the last one itself."""
    out = np.empty(2 * len(samples), np.int16)
    out[0::2] = samples
    out[1:-1:2] = (samples[:-1].astype(np.int32) + samples[1:]) >> 1
    out[-1:] = samples[-1:]
    return out


def described(samples: np.ndarray) -> str:
    """Whole-number features of PCM: samples, peak, mean square, sign changes, CRC-32 of the little-endian samples."""
    crossings = int(np.count_nonzero((samples[1:] < 0) != (samples[:-1] < 0)))
    peak, power = 0, 0
    for at in range(0, len(samples), STRETCH):
        wide = samples[at : at + STRETCH].astype(np.int64)
        peak, power = max(peak, int(np.abs(wide).max())), power + int((wide * wide).sum())
    return f"n={len(samples)};peak={peak};power={power // len(samples)};crossings={crossings};crc={zlib.crc32(samples.astype('<i2').tobytes()):08x}"


def payload_of(data: bytes, unit: int = BLOCK) -> bytes:
    """Bytes with bytes 32 after them up to a positive multiple of `unit`."""
    return data.ljust(max(1, -(-len(data) // unit)) * unit, b" ")


FORMS = (MU_LAW, A_LAW, IMA_ADPCM)


def stored_media(text: Column, form: int | None = None) -> Column:
    """WAVE bytes of texts: each byte of the payload is one 8-bit sample, or its bytes are ADPCM blocks."""

    @F.arrow_udf("binary")
    def run(column: pa.Array) -> pa.Array:
        payloads = map(payload_of, as_bytes(column))
        chosen = ((form or FORMS[zlib.crc32(p) % 3], p) for p in payloads)
        out = pa.array([wave(p, f, block=ADPCM_BLOCK if f == IMA_ADPCM else 1) for f, p in chosen], pa.binary())
        give_back()
        return out

    return run(text)


@arrow_function("binary")
def decoded_pcm(media: pa.Array) -> pa.Array:
    """16-bit little-endian PCM at twice the stored rate."""
    return pa.array([None if x is None else doubled(x).astype("<i2").tobytes() for _, x in decoded(media.to_pylist())], pa.binary())


READ = "struct<payload_bytes:long,payload_sha256:string,tail_crc32:long,media_bytes:long,media_sha256:string,format:int,feature:string>"


@arrow_function(READ)
def read_media(media: pa.Array) -> pa.Array:
    """Digests and features of stored media, all from the bytes read back."""
    rows, media = [], media.to_pylist()
    for m, (payload, samples) in zip(media, decoded(media), strict=True):
        rows.append(
            (None,) * 7 if m is None else
            (len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), len(m), hashlib.sha256(m).hexdigest(), read_wave(m)[0], described(doubled(samples)))
        )
    columns = list(zip(*rows, strict=True)) if rows else [[]] * 7
    kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.int32(), pa.string()]
    names = ["payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "format", "feature"]
    out = pa.StructArray.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=names)
    give_back()
    return out


def media_table(docs: DataFrame, form: int | None = None) -> DataFrame:
    """doc_id, n_bytes and media of each text, written to the shared folder and read again."""
    made = docs.select("doc_id", F.octet_length(F.coalesce("text", F.lit(""))).cast("long").alias("n_bytes"), stored_media(F.col("text"), form).alias("media"))
    return stored(made, "media")


def pcm_table(docs: DataFrame, form: int | None = None) -> DataFrame:
    """doc_id and the resampled PCM of each text's media."""
    return media_table(docs, form).select("doc_id", decoded_pcm("media").alias("pcm"))


def store_pcm(docs: DataFrame, path: str, form: int | None = None) -> None:
    """pcm_table() as Parquet; `path` is one that executors share."""
    pcm_table(docs, form).write.option("compression", "zstd").parquet(path)


def media_digests(docs: DataFrame, form: int | None = None) -> DataFrame:
    """doc_id, n_bytes and what is read back from each text's media."""
    return media_table(docs, form).select("doc_id", "n_bytes", read_media("media").alias("r")).select("doc_id", "n_bytes", "r.*")
