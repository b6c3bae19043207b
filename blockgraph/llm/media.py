"""Operator 10: telephony audio in media columns.

Bytes are kept losslessly as the 8-bit units of a WAV file: mu-law or A-law samples, or blocks of IMA ADPCM
nibbles. Reading parses the container again, expands mu-law and A-law by table, decodes ADPCM step by step over
all blocks of a slice at once, and resamples the 16-bit PCM.

Defined cases: a null or empty text gives one padding unit; equal contents give equal media; a blob that is no
WAV file of these codecs decodes to nulls; an empty table gives empty ones; a text of any length is one blob; other columns stay
as they are, but for one that has the name of the new column (``media``, ``audio`` or the name given), which is replaced.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .scratch import scratch_path
from .text import rows_of, slices, utf8

UNIT = 576
RATE, RESAMPLED = 8000, 16000
#: Format tags of WAV files.
FORMATS = {"alaw": 6, "mulaw": 7, "ima_adpcm": 17}
CODECS = {v: k for k, v in FORMATS.items()}
#: Index moves of IMA ADPCM by the nibble's lower three bits.
INDEX_MOVES = np.array([-1, -1, -1, -1, 2, 4, 6, 8], np.int32)
#: Step sizes of IMA ADPCM.
STEPS = np.array([
    7, 8, 9, 10, 11, 12, 13, 14, 16, 17, 19, 21, 23, 25, 28, 31, 34, 37, 41, 45, 50, 55, 60, 66, 73, 80, 88, 97, 107, 118, 130, 143, 157, 173, 190, 209,
    230, 253, 279, 307, 337, 371, 408, 449, 494, 544, 598, 658, 724, 796, 876, 963, 1060, 1166, 1282, 1411, 1552, 1707, 1878, 2066, 2272, 2499, 2749,
    3024, 3327, 3660, 4026, 4428, 4871, 5358, 5894, 6484, 7132, 7845, 8630, 9493, 10442, 11487, 12635, 13899, 15289, 16818, 18500, 20350, 22385, 24623,
    27086, 29794, 32767,
], np.int32)


def mulaw_table() -> np.ndarray:
    code = ~np.arange(256, dtype=np.int32) & 0xFF
    size = ((((code & 0x0F) << 3) + 0x84) << ((code & 0x70) >> 4)) - 0x84
    return np.where(code & 0x80, -size, size).astype(np.int16)


def alaw_table() -> np.ndarray:
    code = np.arange(256, dtype=np.int32) ^ 0x55
    segment, low = (code & 0x70) >> 4, (code & 0x0F) << 4
    size = np.where(segment == 0, low + 8, (low + 0x108) << np.maximum(segment - 1, 0))
    return np.where(code & 0x80, size, -size).astype(np.int16)


EXPAND = {"mulaw": mulaw_table(), "alaw": alaw_table()}


def decode_adpcm(blocks: np.ndarray) -> np.ndarray:
    """Blocks (rows of bytes: predictor, index, spare byte, nibbles low first) -> samples of each block."""
    n, width = blocks.shape
    out = np.empty((1 + 2 * (width - 4), n), np.int16)
    value = blocks[:, :2].copy().view("<i2")[:, 0].astype(np.int32)
    index = np.minimum(blocks[:, 2], len(STEPS) - 1).astype(np.int32)
    out[0] = value
    columns = np.ascontiguousarray(blocks[:, 4:].T)
    for k in range(width - 4):
        for half in (0, 1):
            nibble = (columns[k] >> 4 if half else columns[k] & 15).astype(np.int32)
            step = STEPS[index]
            move = (step >> 3) + (step >> 2) * (nibble & 1) + (step >> 1) * (nibble >> 1 & 1) + step * (nibble >> 2 & 1)
            value = np.clip(np.where(nibble & 8, value - move, value + move), -32768, 32767)
            index = np.clip(index + INDEX_MOVES[nibble & 7], 0, len(STEPS) - 1)
            out[1 + 2 * k + half] = value
    return np.ascontiguousarray(out.T)


def padded(text: bytes, unit: int = UNIT) -> bytes:
    """The text with bytes 255 up to a positive multiple of the unit."""
    return text + b"\xff" * (max(unit, -(-len(text) // unit) * unit) - len(text))


def to_wav(payload: bytes, codec: str, rate: int = RATE, block: int = UNIT) -> bytes:
    if codec == "ima_adpcm":
        per_block = 1 + 2 * (block - 4)
        fmt = struct.pack("<HHIIHHHH", 17, 1, rate, rate * block // per_block, block, 4, 2, per_block)
        samples = len(payload) // block * per_block
    else:
        fmt = struct.pack("<HHIIHHH", FORMATS[codec], 1, rate, rate, 1, 8, 0)
        samples = len(payload)
    chunks = [(b"fmt ", fmt), (b"fact", struct.pack("<I", samples)), (b"data", payload)]
    body = b"WAVE" + b"".join(name + struct.pack("<I", len(x)) + x + b"\0" * (len(x) % 2) for name, x in chunks)
    return b"RIFF" + struct.pack("<I", len(body)) + body


def read_wav(blob: bytes | None) -> tuple[str, int, int, bytes] | None:
    """codec, rate, block size and payload; None if it is no telephony WAV."""
    if not blob or len(blob) < 12 or blob[:4] != b"RIFF" or blob[8:12] != b"WAVE":
        return None
    at, fmt = 12, None
    while at + 8 <= len(blob):
        name, size = blob[at : at + 4], struct.unpack_from("<I", blob, at + 4)[0]
        if name == b"fmt " and size >= 16:
            fmt = struct.unpack_from("<HHIIHH", blob, at + 8)
        elif name == b"data" and fmt:
            return (CODECS[fmt[0]], fmt[2], fmt[4], blob[at + 8 : at + 8 + size]) if fmt[0] in CODECS else None
        at += 8 + size + size % 2
    return None


def resample(pcm: np.ndarray, source: int, target: int) -> np.ndarray:
    """Linear interpolation in whole numbers."""
    if source == target or not len(pcm):
        return pcm
    at = np.arange(-(-len(pcm) * target // source), dtype=np.int64) * source
    left, part = at // target, at % target
    wide = pcm.astype(np.int64)
    right = np.minimum(left + 1, len(pcm) - 1)
    return ((wide[left] * (target - part) + wide[right] * part) // target).astype(np.int16)


def decode_all(media: list[bytes | None], target: int = RESAMPLED) -> list[tuple[str, bytes, np.ndarray, np.ndarray] | None]:
    """codec, stored payload, PCM as decoded and resampled PCM of each blob; ADPCM blocks of all blobs are decoded together."""
    parsed = [read_wav(m) for m in media]
    by_size: dict[int, list[int]] = {}
    for i, p in enumerate(parsed):
        if p and p[0] == "ima_adpcm" and p[2] > 4:
            by_size.setdefault(p[2], []).append(i)
    pcm: dict[int, np.ndarray] = {}
    for size, which in by_size.items():
        counts = [len(parsed[i][3]) // size for i in which]
        flat = np.frombuffer(b"".join(parsed[i][3][: c * size] for i, c in zip(which, counts, strict=True)), np.uint8).reshape(-1, size)
        samples = decode_adpcm(flat)
        for i, part in zip(which, np.split(samples, np.cumsum(counts)[:-1]), strict=True):
            pcm[i] = part.reshape(-1)
    out = []
    for i, p in enumerate(parsed):
        if p and p[0] in EXPAND:
            pcm[i] = EXPAND[p[0]][np.frombuffer(p[3], np.uint8)]
        out.append((p[0], p[3], pcm[i], resample(pcm[i], p[1], target)) if p and i in pcm else None)
    return out


def feature(codec: str, pcm: np.ndarray, stored: np.ndarray) -> str:
    """Whole-number features: samples, peak, mean level, zero crossings, and the CRC of the resampled PCM."""
    wide = pcm.astype(np.int32)
    level = np.abs(wide)
    negative = wide < 0
    return f"{codec};n={len(wide)};peak={int(level.max(initial=0))};mean={int(level.sum(dtype=np.int64)) // max(1, len(wide))};zc={int(np.count_nonzero(negative[1:] != negative[:-1]))};pcm{RESAMPLED}={zlib.crc32(stored.astype('<i2').tobytes()):08x}"


def codec_of(payload: bytes) -> str:
    """The content decides which of the three forms keeps it."""
    return ("mulaw", "alaw", "ima_adpcm")[zlib.crc32(payload) % 3]


def store_media(docs: DataFrame, codec: str | None = None, column: str = "media") -> DataFrame:
    """All columns of ``docs`` plus ``column``: the text's bytes as a telephony WAV."""

    @F.pandas_udf("binary")
    def build(texts: pd.Series) -> pd.Series:
        payloads = [padded((t or "").encode()) for t in texts.where(texts.notna(), None)]
        return pd.Series([to_wav(p, codec or codec_of(p)) for p in payloads], dtype=object)

    return docs.withColumn(column, build("text"))


def decode_media(df: DataFrame, column: str = "media", target: int = RESAMPLED, into: str = "audio") -> DataFrame:
    """All columns plus ``into``: struct(codec, payload, rate, pcm), pcm little-endian 16-bit at the target rate."""

    @F.pandas_udf("struct<codec: string, payload: binary, rate: int, pcm: binary>")
    def decode(blobs: pd.Series) -> pd.DataFrame:
        found = decode_all([None if b is None else bytes(b) for b in blobs], target)
        return pd.DataFrame([(None,) * 4 if f is None else (f[0], f[1], target, f[3].astype("<i2").tobytes()) for f in found], columns=["codec", "payload", "rate", "pcm"])

    return df.withColumn(into, decode(column))


SUMMARY = "doc_id bigint, n_bytes bigint, payload_bytes bigint, payload_sha256 string, tail_crc32 bigint, media_bytes bigint, media_sha256 string, feature string"


def write_media(docs: DataFrame, path: str, codec: str | None = None) -> None:
    """Store (doc_id, n_bytes, media) of every row: the text's bytes, their number before padding, as a telephony WAV."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = rows_of(batch, "doc_id")
            data, offs = utf8(rows_of(batch, "text"))
            for i, j in slices(offs, 2 << 20):
                raw, cuts = data[offs[i] : offs[j]].tobytes(), (offs[i : j + 1] - offs[i]).tolist()
                media = [to_wav(p, codec or codec_of(p)) for p in (padded(raw[a:b]) for a, b in zip(cuts, cuts[1:], strict=False))]
                yield pa.RecordBatch.from_arrays([ids.slice(i, j - i), pa.array(np.diff(offs[i : j + 1])), pa.array(media, pa.binary())], ["doc_id", "n_bytes", "media"])

    docs.select("doc_id", "text").mapInArrow(run, "doc_id bigint, n_bytes bigint, media binary").write.option("compression", "zstd").parquet(path)


def read_media(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("doc_id bigint, n_bytes bigint, media binary").parquet(path)


def write_pcm(media: DataFrame, path: str, target: int = RESAMPLED) -> None:
    """Store (doc_id, codec, rate, pcm) of every stored blob: 16-bit PCM at the target rate, a table 4 to 8 times the bytes of the media."""
    decode_media(media.select("doc_id", "media"), "media", target).select("doc_id", "audio.codec", "audio.rate", "audio.pcm").write.option("compression", "zstd").parquet(path)


def media_summary(stored: DataFrame) -> DataFrame:
    """Describe stored blobs (doc_id, n_bytes, media): payload and PCM are decoded from what was read back."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, sizes = rows_of(batch, "doc_id"), rows_of(batch, "n_bytes")
            blobs = rows_of(batch, "media")
            _, offs = utf8(blobs)
            for i, j in slices(offs, 2 << 20):
                media = blobs.slice(i, j - i).to_pylist()
                rows = []
                for blob, (codec, payload, pcm, resampled) in zip(media, decode_all(media), strict=True):
                    rows.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]), len(blob), hashlib.sha256(blob).hexdigest(), feature(codec, pcm, resampled)))
                columns = list(zip(*rows, strict=True))
                yield pa.RecordBatch.from_arrays(
                    [ids.slice(i, j - i), sizes.slice(i, j - i), *(pa.array(c, t) for c, t in zip(columns, (pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()), strict=True))],
                    ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"],
                )

    return stored.select("doc_id", "n_bytes", "media").mapInArrow(run, SUMMARY)


def op10_telephony(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every text is written to a media table, and the result comes from the table as read back. PCM is resampled and described; storing it
    too (:func:`write_pcm`) would take 4 to 8 times the input's bytes."""
    path = scratch_path(spark, "media")
    write_media(spark.read.parquet(f"{sf_dir}/documents.parquet"), path)
    return media_summary(read_media(spark, path))
