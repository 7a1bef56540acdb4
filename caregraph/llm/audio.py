"""Media columns: telephony audio.

mu-law and A-law samples are expanded by tables of 256 entries, built from the
companding rules; IMA ADPCM blocks are decoded sample by sample with numpy, all
blocks of a clip at once. Clips are RIFF/WAVE bytes in a binary column; decoded
audio is stored again as 16-bit PCM at a target rate.
"""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: RIFF format tags.
PCM, ALAW, MULAW, IMA_ADPCM = 1, 6, 7, 17
#: IMA ADPCM step sizes and index changes.
STEPS = np.array([
    7, 8, 9, 10, 11, 12, 13, 14, 16, 17, 19, 21, 23, 25, 28, 31, 34, 37, 41, 45, 50, 55, 60, 66, 73, 80, 88, 97, 107, 118, 130, 143, 157, 173, 190, 209, 230, 253, 279, 307, 337, 371, 408, 449, 494, 544, 598, 658, 724, 796, 876, 963, 1060, 1166, 1282, 1411, 1552, 1707, 1878, 2066, 2272, 2499, 2749, 3024, 3327, 3660, 4026, 4428, 4871, 5358, 5894, 6484, 7132, 7845, 8630, 9493, 10442, 11487, 12635, 13899, 15289, 16818, 18500, 20350, 22385, 24623, 27086, 29794, 32767,
], dtype=np.int32)
INDEX_CHANGE = np.array([-1, -1, -1, -1, 2, 4, 6, 8] * 2, dtype=np.int32)
UNIT = 64
"""A text's payload is zero-padded to a positive multiple of so many bytes."""


def _mulaw() -> np.ndarray:
    code = ~np.arange(256) & 0xFF
    size = (((code & 15) << 3) + 132 << (code >> 4 & 7)) - 132
    return np.where(code & 128, -size, size).astype(np.int16)


def _alaw() -> np.ndarray:
    code = np.arange(256) ^ 0x55
    part, step = code >> 4 & 7, (code & 15) << 4
    size = np.where(part == 0, step + 8, step + 264 << np.maximum(part - 1, 0))
    return np.where(code & 128, size, -size).astype(np.int16)


TABLES = {MULAW: _mulaw(), ALAW: _alaw()}


def wave(tag: int, rate: int, bits: int, data: bytes, align: int = 1, extra: bytes = b"", samples: int | None = None) -> bytes:
    """A mono RIFF/WAVE file. ``align``: bytes of a block; ``extra``: of the format's own fields."""
    fmt = struct.pack("<HHIIHHH", tag, 1, rate, rate * align if tag != IMA_ADPCM else rate // 2, align, bits, len(extra)) + extra
    fact = struct.pack("<I", len(data) if samples is None else samples)
    body = b"WAVE" + b"".join(name + struct.pack("<I", len(x)) + x + b"\0" * (len(x) & 1) for name, x in ((b"fmt ", fmt), (b"fact", fact), (b"data", data)))
    return b"RIFF" + struct.pack("<I", len(body)) + body


def chunks(media: bytes) -> dict[bytes, memoryview]:
    if media[:4] != b"RIFF" or media[8:12] != b"WAVE":
        raise ValueError("not a RIFF/WAVE file")
    out, at, view = {}, 12, memoryview(media)
    while at + 8 <= len(media):
        n = struct.unpack_from("<I", media, at + 4)[0]
        out.setdefault(bytes(view[at : at + 4]), view[at + 8 : at + 8 + n])
        at += 8 + n + (n & 1)
    return out


def adpcm_decode(data: bytes, align: int) -> np.ndarray:
    """Samples of whole IMA blocks; each step decodes one sample of every block. A cut-off last block is padded with zeros."""
    n = -(-len(data) // align)
    blocks = np.frombuffer(bytes(data).ljust(n * align, b"\0"), np.uint8).reshape(n, align)
    value = blocks[:, :2].copy().view("<i2")[:, 0].astype(np.int32)
    index = np.minimum(blocks[:, 2].astype(np.int32), 88)
    codes = np.stack([blocks[:, 4:] & 15, blocks[:, 4:] >> 4], axis=2).reshape(n, -1)
    out = np.empty((n, codes.shape[1] + 1), np.int16)
    out[:, 0] = value
    for k in range(codes.shape[1]):
        code, step = codes[:, k].astype(np.int32), STEPS[index]
        change = (step >> 3) + np.where(code & 4, step, 0) + np.where(code & 2, step >> 1, 0) + np.where(code & 1, step >> 2, 0)
        value = np.clip(np.where(code & 8, value - change, value + change), -32768, 32767)
        index = np.clip(index + INDEX_CHANGE[code], 0, 88)
        out[:, k + 1] = value
    return out.reshape(-1)


def adpcm_encode(pcm: np.ndarray, align: int = 256) -> bytes:
    """IMA blocks of ``align`` bytes; the last is padded by its last sample. Used by tests and for storing."""
    per = (align - 4) * 2 + 1
    n = max(1, -(-len(pcm) // per))
    x = np.pad(pcm.astype(np.int32), (0, n * per - len(pcm)), mode="edge" if len(pcm) else "constant").reshape(n, per)
    # A block starts at the step that fits its changes.
    value, index = x[:, 0].copy(), np.clip(np.searchsorted(STEPS, np.abs(np.diff(x, axis=1)).mean(axis=1)), 0, 88).astype(np.int32)
    out = np.zeros((n, align), np.uint8)
    out[:, :2] = value.astype("<i2").view(np.uint8).reshape(n, 2)
    out[:, 2] = index
    codes = np.empty((n, per - 1), np.uint8)
    for k in range(1, per):
        step = STEPS[index]
        gap = x[:, k] - value
        code = np.minimum(np.abs(gap) * 4 // step, 7)
        change = (step >> 3) + np.where(code & 4, step, 0) + np.where(code & 2, step >> 1, 0) + np.where(code & 1, step >> 2, 0)
        code = code | np.where(gap < 0, 8, 0)
        value = np.clip(np.where(code & 8, value - change, value + change), -32768, 32767)
        index = np.clip(index + INDEX_CHANGE[code], 0, 88)
        codes[:, k - 1] = code
    out[:, 4:] = codes[:, ::2] | codes[:, 1::2] << 4
    return out.tobytes()


class Unreadable(ValueError):
    """A clip that isn't decoded, and why."""


def decode(media: bytes) -> tuple[np.ndarray, int]:
    """(16-bit samples, rate) of a clip in any of the four formats; several channels become their mean (ADPCM: mono only)."""
    try:
        c = chunks(media)
    except (ValueError, struct.error) as e:
        raise Unreadable("not a RIFF/WAVE file") from e
    if len(c.get(b"fmt ", b"")) < 16 or b"data" not in c:
        raise Unreadable("no format or no data")
    tag, channels, rate, _, align, bits = struct.unpack_from("<HHIIHH", c[b"fmt "])
    data = bytes(c[b"data"])
    if not channels or not rate:
        raise Unreadable("no channels or no rate")
    if tag == IMA_ADPCM and channels == 1 and align > 4:
        pcm = adpcm_decode(data, align)
        return pcm[: struct.unpack("<I", c[b"fact"])[0]] if len(c.get(b"fact", b"")) == 4 else pcm, rate
    if tag == PCM and bits == 16:
        x = np.frombuffer(data[: len(data) // 2 * 2], "<i2")
    elif tag == PCM and bits == 8:
        x = (np.frombuffer(data, np.uint8).astype(np.int16) - 128) * 256
    elif tag in TABLES and bits == 8:
        x = TABLES[tag][np.frombuffer(data, np.uint8)]
    else:
        raise Unreadable(f"format {tag} of {bits} bits and {channels} channels")
    if channels > 1:
        x = np.rint(x[: len(x) // channels * channels].reshape(-1, channels).mean(axis=1)).astype(np.int16)
    return x, rate


def resample(pcm: np.ndarray, rate: int, to: int) -> np.ndarray:
    """Linear interpolation on the output's sample times."""
    if rate == to or not len(pcm):
        return pcm.astype(np.int16)
    at = np.arange(len(pcm) * to // rate, dtype=np.float64) * rate / to
    low = at.astype(np.int64)
    high = np.minimum(low + 1, len(pcm) - 1)
    part = at - low
    return np.rint(pcm[low] * (1 - part) + pcm[high] * part).astype(np.int16)


def to_pcm(media: bytes | None, rate: int = 16000) -> bytes | None:
    """The clip as a 16-bit PCM file at ``rate``; null stays null."""
    if media is None:
        return None
    pcm, own = decode(media)
    out = resample(pcm, own, rate)
    return wave(PCM, rate, 16, out.astype("<i2").tobytes(), 2, samples=len(out))


def feature(pcm: np.ndarray) -> str:
    """Samples, peak, root mean square, sign changes."""
    x = pcm.astype(np.float64)
    return f"n={len(x)};peak={int(np.abs(x).max()) if len(x) else 0};rms={np.sqrt(np.mean(x * x)) if len(x) else 0:.3f};zc={int(np.count_nonzero(np.signbit(x[1:]) != np.signbit(x[:-1])))}"


def store_pcm(clips: DataFrame, media: str = "media", rate: int = 16000, out: str = "pcm") -> DataFrame:
    """``clips`` with columns ``out`` and ``out``_status: each clip of any format as resampled 16-bit PCM, and ``ok``.

    Null clips, and clips that can't be read, are null, with ``null`` or the reason
    as status; none fails the job. A clip that is cut off is read as far as it goes. Columns of these names are replaced.
    """

    @F.pandas_udf("pcm binary, status string")
    def run(col: pd.Series) -> pd.DataFrame:
        rows = []
        for m in col:
            try:
                rows.append((to_pcm(m, rate), "null" if m is None else "ok"))
            except Unreadable as e:
                rows.append((None, str(e)))
        return pd.DataFrame(rows, columns=["pcm", "status"])

    both = clips.withColumn("__cg_pcm", run(F.col(media)))
    return both.withColumn(out, F.col("__cg_pcm.pcm")).withColumn(out + "_status", F.col("__cg_pcm.status")).drop("__cg_pcm")


def encode_texts(docs: DataFrame, text: str = "text", out: str = "media") -> DataFrame:
    """``docs`` with column ``out``: the text's UTF-8 bytes, zero-padded to a positive multiple of 64, as 8-bit mu-law samples of a clip at 8 kHz. Null counts as empty."""

    @F.pandas_udf("binary")
    def run(col: pd.Series) -> pd.Series:
        def one(t: str | None) -> bytes:
            raw = (t or "").encode()
            return wave(MULAW, 8000, 8, raw.ljust(max(UNIT, -(-len(raw) // UNIT) * UNIT), b"\0"))

        return col.map(one, na_action=None)

    return docs.withColumn(out, run(F.col(text)))


CLIPS = 1000
"""Clips whose ADPCM blocks are coded together."""


def adpcm_features(clips: list[np.ndarray], align: int = 256) -> list[str]:
    """Features of the clips after a way through ADPCM files; the blocks of all clips are encoded, and decoded, at once."""
    per = (align - 4) * 2 + 1
    padded = [np.pad(x, (0, -len(x) % per), mode="edge") for x in clips]
    coded = adpcm_encode(np.concatenate(padded), align) if clips else b""
    at, media = 0, []
    for x in padded:
        n = len(x) // per * align
        media.append(coded[at : at + n])
        at += n
    # Each clip's file holds its own blocks; they are read back together.
    files = [wave(IMA_ADPCM, 8000, 4, m, align, struct.pack("<H", per), len(x)) for m, x in zip(media, clips, strict=True)]
    data = [bytes(chunks(f)[b"data"]) for f in files]
    back = adpcm_decode(b"".join(data), align) if data else np.empty(0, np.int16)
    ends = np.cumsum([len(x) for x in padded])
    return [feature(back[e - len(p) : e - len(p) + len(x)]) for e, p, x in zip(ends, padded, clips, strict=True)]


def describe(clips: DataFrame) -> DataFrame:
    """(doc_id, n_bytes, digests of the samples read back and of the stored form, features); columns ``doc_id, n_bytes, media`` (mu-law clips) are read.

    ``feature``: of the resampled audio, which is stored as PCM (``pcm_sha256``); ``alaw_feature``: of the same bytes read as A-law; ``adpcm_feature``: of the audio after ADPCM.
    """
    kind = "payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, pcm_sha256 string, alaw_feature string, adpcm_feature string"

    @F.pandas_udf(kind)
    def run(col: pd.Series) -> pd.DataFrame:
        rows, first = [], []
        for media in col:
            raw = bytes(chunks(media)[b"data"])
            stored = to_pcm(media)
            pcm, _ = decode(stored)
            alaw, _ = decode(wave(ALAW, 8000, 8, raw))
            rows.append((len(raw), hashlib.sha256(raw).hexdigest(), zlib.crc32(raw[-UNIT:]), len(media), hashlib.sha256(media).hexdigest(), feature(pcm), hashlib.sha256(stored).hexdigest(), feature(alaw)))
            first.append(decode(media)[0])
        adpcm, at, n = [], 0, 0
        for k, x in enumerate(first):
            n += len(x)
            if n >= 1 << 20 or k + 1 - at >= CLIPS or k == len(first) - 1:
                adpcm += adpcm_features(first[at : k + 1])
                at, n = k + 1, 0
        names = [c.split()[0] for c in kind.split(", ")]
        return pd.DataFrame(rows, columns=names[:-1]).assign(adpcm_feature=adpcm)

    return clips.select("doc_id", "n_bytes", run("media").alias("d")).select("doc_id", "n_bytes", "d.*")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``describe`` of every text of ``documents`` as mu-law audio; null texts count as empty, repeated rows give equal rows."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    docs = docs.withColumn("n_bytes", F.octet_length(F.coalesce("text", F.lit(""))).cast("long"))
    return describe(encode_texts(docs))
