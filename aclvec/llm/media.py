"""Telephony audio in a column: companded samples, block ADPCM and stored PCM.

Mu-law and A-law bytes expand by 256-entry tables built from the companding
rules. IMA ADPCM is decoded sample by sample but across all blocks of a run of
clips at once. Expanded speech is resampled and stored as 16-bit PCM in a WAVE
file, read back from there and described.

Defined results: a null text is the empty payload, which is padded to one frame;
equal payloads give equal files and features; repeated rows give repeated rows.
A file that is no WAVE file of these kinds raises ValueError.
"""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from aclvec.llm.common import id_and_bytes, narrow_batches, per_text, stored, table

# Format tags of the WAVE container.
PCM, ALAW, MULAW, IMA = 1, 6, 7, 17
# IMA ADPCM index changes by the low three bits of a code.
IMA_INDEX = [-1, -1, -1, -1, 2, 4, 6, 8]

#: Bytes of a frame: payloads are padded with 255 to a positive multiple.
FRAME = 576
#: Bytes of an ADPCM block: a frame is a whole number of them.
BLOCK = 36
RATE, OUT_RATE = 8000, 16000


def mulaw_table() -> np.ndarray:
    """16-bit value of each mu-law byte."""
    code = ~np.arange(256) & 0xFF
    size = ((((code & 15) << 3) + 132) << ((code >> 4) & 7)) - 132
    return np.where(code & 128, -size, size).astype(np.int16)


def alaw_table() -> np.ndarray:
    """16-bit value of each A-law byte."""
    code = np.arange(256) ^ 0x55
    seg, low = (code >> 4) & 7, (code & 15) << 4
    size = np.where(seg == 0, low + 8, (low + 264) << np.maximum(seg - 1, 0))
    return np.where(code & 128, size, -size).astype(np.int16)


def ima_steps() -> np.ndarray:
    """The 89 quantiser steps."""
    # IMA ADPCM step sizes.
    return np.array([
        7, 8, 9, 10, 11, 12, 13, 14, 16, 17, 19, 21, 23, 25, 28, 31, 34, 37, 41, 45, 50, 55, 60, 66, 73, 80, 88, 97, 107, 118,
        130, 143, 157, 173, 190, 209, 230, 253, 279, 307, 337, 371, 408, 449, 494, 544, 598, 658, 724, 796, 876, 963, 1060,
        1166, 1282, 1411, 1552, 1707, 1878, 2066, 2272, 2499, 2749, 3024, 3327, 3660, 4026, 4428, 4871, 5358, 5894, 6484, 7132,
        7845, 8630, 9493, 10442, 11487, 12635, 13899, 15289, 16818, 18500, 20350, 22385, 24623, 27086, 29794, 32767,
    ])


def adpcm_decode(blocks: np.ndarray) -> np.ndarray:
    """16-bit samples of IMA ADPCM blocks (n, block bytes), one channel: four header bytes, then codes, low nibble first."""
    steps = ima_steps()
    move = np.array(IMA_INDEX * 2)
    head = np.ascontiguousarray(blocks[:, :2]).view("<i2")[:, 0].astype(np.int64)
    index = np.clip(blocks[:, 2].astype(np.int64), 0, 88)
    codes = np.stack((blocks[:, 4:] & 15, blocks[:, 4:] >> 4), axis=2).reshape(len(blocks), -1)
    out = np.empty((len(blocks), 1 + codes.shape[1]), np.int16)
    out[:, 0] = value = head
    for t in range(codes.shape[1]):
        c, step = codes[:, t], steps[index]
        delta = (step >> 3) + (step >> 2) * (c & 1) + (step >> 1) * ((c >> 1) & 1) + step * ((c >> 2) & 1)
        value = np.clip(value + np.where(c & 8, -delta, delta), -32768, 32767)
        index = np.clip(index + move[c], 0, 88)
        out[:, 1 + t] = value
    return out


def adpcm_encode(samples: np.ndarray) -> np.ndarray:
    """Blocks of IMA ADPCM for rows of 16-bit samples (n, 1 + an even count)."""
    steps = ima_steps()
    move = np.array(IMA_INDEX * 2)
    n, t_all = samples.shape
    value, index = samples[:, 0].astype(np.int64), np.zeros(n, np.int64)
    codes = np.zeros((n, t_all - 1), np.uint8)
    for t in range(1, t_all):
        step = steps[index]
        diff = samples[:, t] - value
        left, c = np.abs(diff), np.where(diff < 0, 8, 0)
        for bit, part in ((4, step), (2, step >> 1), (1, step >> 2)):
            on = left >= part
            c, left = c + bit * on, left - part * on
        delta = (step >> 3) + (step >> 2) * (c & 1) + (step >> 1) * ((c >> 1) & 1) + step * ((c >> 2) & 1)
        value = np.clip(value + np.where(c & 8, -delta, delta), -32768, 32767)
        index = np.clip(index + move[c], 0, 88)
        codes[:, t - 1] = c
    head = np.zeros((n, 4), np.uint8)
    head[:, :2] = np.ascontiguousarray(samples[:, 0].astype("<i2")).view(np.uint8).reshape(n, 2)
    return np.concatenate((head, codes[:, ::2] | (codes[:, 1::2] << 4)), axis=1)


def wave(tag: int, data: bytes, rate: int, block: int = 1, bits: int = 8, extra: bytes = b"") -> bytes:
    """A one-channel WAVE file of `data`."""
    form = struct.pack("<HHIIHH", tag, 1, rate, rate * bits // 8, block, bits)
    if tag != PCM:
        form += struct.pack("<H", len(extra)) + extra
    parts = b"fmt " + struct.pack("<I", len(form)) + form
    if tag != PCM:
        parts += b"fact" + struct.pack("<II", 4, len(data) * 8 // bits)
    parts += b"data" + struct.pack("<I", len(data)) + data + b"\0" * (len(data) & 1)
    return b"RIFF" + struct.pack("<I", 4 + len(parts)) + b"WAVE" + parts


def parse_wave(media: bytes) -> tuple[int, int, int, memoryview]:
    """Format tag, sample rate, block size and the sample bytes of a WAVE file."""
    view = memoryview(media)
    if len(view) < 12 or bytes(view[:4]) != b"RIFF" or bytes(view[8:12]) != b"WAVE":
        raise ValueError("not a WAVE file")
    at, tag, rate, block = 12, None, 0, 1
    while at + 8 <= len(view):
        name, size = bytes(view[at : at + 4]), struct.unpack_from("<I", view, at + 4)[0]
        if name == b"fmt ":
            tag, _, rate, _, block, _ = struct.unpack_from("<HHIIHH", view, at + 8)
        elif name == b"data":
            if tag is None:
                raise ValueError("samples before their format")
            return tag, rate, block, view[at + 8 : at + 8 + size]
        at += 8 + size + (size & 1)
    raise ValueError("a WAVE file without samples")


def samples(media: bytes, tables: dict[int, np.ndarray] | None = None) -> tuple[int, np.ndarray]:
    """Rate and 16-bit samples of a stored clip of any of the four kinds."""
    tables = tables or {MULAW: mulaw_table(), ALAW: alaw_table()}
    tag, rate, block, data = parse_wave(media)
    raw = np.frombuffer(data, np.uint8)
    if tag in tables:
        return rate, tables[tag][raw]
    if tag == IMA:
        return rate, adpcm_decode(raw[: len(raw) // block * block].reshape(-1, block)).ravel()
    if tag == PCM:
        return rate, raw[: len(raw) // 2 * 2].view("<i2")
    raise ValueError(f"WAVE format {tag} is not supported")


def resample(x: np.ndarray, rate: int, out_rate: int) -> np.ndarray:
    """Linear interpolation of 16-bit samples to another rate; the last sample is held."""
    if rate == out_rate or len(x) < 2:
        return x
    if out_rate == 2 * rate:
        wide = x.astype(np.int32)
        out = np.empty(2 * len(x), np.int16)
        out[::2] = x
        out[1:-1:2] = (wide[:-1] + wide[1:]) >> 1
        out[-1] = x[-1]
        return out
    n = len(x) * out_rate // rate
    num = np.arange(n, dtype=np.int64) * rate
    i = np.minimum(num // out_rate, len(x) - 1)
    j, part = np.minimum(i + 1, len(x) - 1), num % out_rate
    return ((x[i].astype(np.int64) * (out_rate - part) + x[j].astype(np.int64) * part) // out_rate).astype(np.int16)


def padded(text: bytes) -> bytes:
    return text + b"\xff" * (-len(text) % FRAME if text else FRAME)


def encode_media(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes and media: the padded text as the samples of a mu-law WAVE file."""

    def work(texts):
        return {"n_bytes": [len(t) for t in texts], "media": [wave(MULAW, padded(t), RATE) for t in texts]}

    return per_text(id_and_bytes(docs), "n_bytes long, media binary", lambda: work)


def to_pcm(media: DataFrame, out_rate: int = OUT_RATE) -> DataFrame:
    """The columns of `media` with `media` as 16-bit PCM at `out_rate`, whatever the kind of file."""

    def work(files):
        out = []
        for f in files:
            rate, x = samples(f)
            out.append(wave(PCM, resample(x, rate, out_rate).astype("<i2").tobytes(), out_rate, 2, 16))
        return {"media": out}

    return per_text(media.withColumnRenamed("media", "text"), "media binary", lambda: work)


def describe(pcm: np.ndarray) -> str:
    """Level, peak, zero crossings and checksum of a clip's samples."""
    wide = pcm.astype(np.int64)
    crossings = int(np.count_nonzero((pcm[1:] ^ pcm[:-1]) < 0))
    return f"n={len(pcm)};sum={int(wide.sum())};energy={int((wide * wide).sum())};peak={int(np.abs(wide).max()) if len(pcm) else 0};zc={crossings};crc={zlib.crc32(pcm.tobytes()):08x}"


def read_media(media: DataFrame, out_rate: int = OUT_RATE) -> DataFrame:
    """Digests of stored mu-law clips, and the speech that the payload holds in each coding.

    The payload is read back, expanded as mu-law and resampled into `pcm`, a WAVE
    file of 16-bit samples. The same bytes are also heard as A-law and as blocks
    of ADPCM (`alaw`, `adpcm`: features of the resampled speech).
    """

    def make():
        tables = {MULAW: mulaw_table(), ALAW: alaw_table()}

        def work(files):
            out = {k: [] for k in ("payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "alaw", "adpcm", "pcm")}
            payloads = [bytes(parse_wave(f)[3]) for f in files]
            # Blocks of all clips are decoded together; a clip is a whole number of blocks.
            speech = adpcm_decode(np.frombuffer(b"".join(payloads), np.uint8).reshape(-1, BLOCK))
            ends = np.cumsum([len(p) // BLOCK for p in payloads]).tolist()
            for f, payload, begin, end in zip(files, payloads, [0, *ends], ends, strict=False):
                rate, x = samples(f, tables)
                out["payload_bytes"].append(len(payload))
                out["payload_sha256"].append(hashlib.sha256(payload).hexdigest())
                out["tail_crc32"].append(zlib.crc32(payload[-32:]))
                out["media_bytes"].append(len(f))
                out["media_sha256"].append(hashlib.sha256(f).hexdigest())
                out["alaw"].append(describe(resample(tables[ALAW][np.frombuffer(payload, np.uint8)], rate, out_rate)))
                out["adpcm"].append(describe(resample(speech[begin:end].ravel(), rate, out_rate)))
                out["pcm"].append(wave(PCM, resample(x, rate, out_rate).astype("<i2").tobytes(), out_rate, 2, 16))
            return out

        return work

    schema = "payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, alaw string, adpcm string, pcm binary"
    return per_text(media.select("doc_id", "n_bytes", F.col("media").alias("text")), schema, make)


def described(clips: DataFrame) -> DataFrame:
    """The columns of `clips` with the size, digest and features of their `pcm` in its place."""

    def work(files):
        return {"pcm_bytes": [len(f) for f in files], "pcm_sha256": [hashlib.sha256(f).hexdigest() for f in files], "feature": [describe(samples(f)[1]) for f in files]}

    return per_text(clips.withColumnRenamed("pcm", "text"), "pcm_bytes long, pcm_sha256 string, feature string", lambda: work)


def op2_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every whole text stored as telephony samples, read back, its resampled speech stored, read back and described."""
    narrow_batches(spark)
    clips = read_media(encode_media(table(spark, sf_dir, "documents")))
    return described(stored(clips, "zstd", 16 << 20))
