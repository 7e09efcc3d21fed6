"""Telephony audio in binary columns: companded samples, ADPCM blocks, containers, resampling.

All codecs work on whole arrays: companded bytes expand through 256-entry
tables made from their defining rule, and ADPCM decodes every block of a
stream side by side, one sample step at a time.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import CHUNK_BYTES, extended, new_path, text_slices
from .words import raw_bytes

#: Format tags of the RIFF/WAVE container.
PCM, ALAW, MULAW, IMA = 1, 6, 7, 17
RATE = 8000


def mulaw_table() -> np.ndarray:
    """16-bit sample of each mu-law byte: sign, 3-bit segment, 4-bit step, all inverted."""
    u = ~np.arange(256, dtype=np.uint8)
    size = ((((u & 15).astype(np.int32) << 3) + 132) << ((u >> 4) & 7)) - 132
    return np.where(u & 128, -size, size).astype(np.int16)


def alaw_table() -> np.ndarray:
    """16-bit sample of each A-law byte: even bits inverted, segment 0 and 1 share their step."""
    a = np.arange(256, dtype=np.uint8) ^ 0x55
    seg, step = ((a >> 4) & 7).astype(np.int32), ((a & 15).astype(np.int32) << 4) + 8
    size = np.where(seg == 0, step, (step + 256) << np.maximum(seg - 1, 0))
    return np.where(a & 128, size, -size).astype(np.int16)


MULAW_TABLE, ALAW_TABLE = mulaw_table(), alaw_table()


def _nearest(table: np.ndarray, pcm: np.ndarray) -> np.ndarray:
    """The byte whose sample is nearest; ties go to the lower sample."""
    order = np.argsort(table, kind="stable").astype(np.uint8)
    levels = table[order].astype(np.int32)
    return order[np.searchsorted((levels[1:] + levels[:-1]) / 2, pcm.astype(np.int32), "left")]


def encode_companded(pcm: np.ndarray, tag: int = MULAW) -> bytes:
    return _nearest(MULAW_TABLE if tag == MULAW else ALAW_TABLE, pcm).tobytes()


def expand(data: bytes, tag: int = MULAW) -> np.ndarray:
    return (MULAW_TABLE if tag == MULAW else ALAW_TABLE)[np.frombuffer(data, np.uint8)]


#: The index moves of 4-bit IMA ADPCM codes (magnitude 0 to 7).
IMA_MOVES = np.array([-1, -1, -1, -1, 2, 4, 6, 8])
#: The 89 step sizes of IMA ADPCM.
IMA_STEPS = np.array([
    7, 8, 9, 10, 11, 12, 13, 14, 16, 17, 19, 21, 23, 25, 28, 31, 34, 37, 41, 45, 50, 55, 60, 66, 73, 80, 88, 97, 107, 118, 130, 143, 157, 173, 190, 209, 230, 253, 279, 307, 337, 371, 408, 449, 494, 544, 598, 658, 724, 796, 876, 963, 1060, 1166, 1282, 1411, 1552, 1707, 1878, 2066, 2272, 2499, 2749, 3024, 3327, 3660, 4026, 4428, 4871, 5358, 5894, 6484, 7132, 7845, 8630, 9493, 10442, 11487, 12635, 13899, 15289, 16818, 18500, 20350, 22385, 24623, 27086, 29794, 32767,
])


def _ima_step(value: np.ndarray, index: np.ndarray, code: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    step, size = IMA_STEPS[index], code & 7
    delta = (step >> 3) + np.where(size & 4, step, 0) + np.where(size & 2, step >> 1, 0) + np.where(size & 1, step >> 2, 0)
    return np.clip(value + np.where(code & 8, -delta, delta), -32768, 32767), np.clip(index + IMA_MOVES[size], 0, 88)


def decode_ima(data: bytes, block: int = 256) -> np.ndarray:
    """Mono IMA ADPCM to 16-bit samples; all blocks advance together.  A last partial block is decoded as far as it goes."""
    whole = len(data) // block * block
    parts = []
    for piece, size in ((data[:whole], block), (data[whole:], len(data) - whole)):
        if size < 4 or not piece:
            continue
        blocks = np.frombuffer(piece, np.uint8).reshape(-1, size)
        value = blocks[:, :2].copy().view("<i2")[:, 0].astype(np.int64)
        index = np.minimum(blocks[:, 2].astype(np.int64), 88)
        codes = np.stack([blocks[:, 4:] & 15, blocks[:, 4:] >> 4], axis=2).reshape(len(blocks), -1)
        out = np.empty((len(blocks), 1 + codes.shape[1]), np.int16)
        out[:, 0] = value
        for k in range(codes.shape[1]):
            value, index = _ima_step(value, index, codes[:, k])
            out[:, k + 1] = value
        parts.append(out.ravel())
    return np.concatenate(parts) if parts else np.zeros(0, np.int16)


def encode_ima(pcm: np.ndarray, block: int = 256) -> bytes:
    """16-bit mono samples to IMA ADPCM blocks, all blocks side by side; the end is padded with the last sample."""
    per = 1 + 2 * (block - 4)
    if not len(pcm):
        return b""
    rows = np.pad(pcm.astype(np.int64), (0, -len(pcm) % per), mode="edge").reshape(-1, per)
    value, index = rows[:, 0].copy(), np.zeros(len(rows), np.int64)
    codes = np.zeros((len(rows), per - 1), np.uint8)
    for k in range(1, per):
        step, diff = IMA_STEPS[index], rows[:, k] - value
        code = np.minimum(np.abs(diff) * 4 // step, 7) | np.where(diff < 0, 8, 0)
        value, index = _ima_step(value, index, code)
        codes[:, k - 1] = code
    head = np.zeros((len(rows), 4), np.uint8)
    head[:, :2] = rows[:, :1].astype("<i2").view(np.uint8).reshape(-1, 2)
    return np.hstack([head, codes[:, ::2] | codes[:, 1::2] << 4]).astype(np.uint8).tobytes()


def wave(data: bytes, tag: int = MULAW, rate: int = RATE, block: int = 1) -> bytes:
    """A mono RIFF/WAVE file around coded samples."""
    bits = {PCM: 16, ALAW: 8, MULAW: 8, IMA: 4}[tag]
    align = {PCM: 2, ALAW: 1, MULAW: 1, IMA: block}[tag]
    extra = struct.pack("<HH", 2, 1 + 2 * (block - 4)) if tag == IMA else b"" if tag == PCM else struct.pack("<H", 0)
    samples = len(data) // align * (1 + 2 * (block - 4)) if tag == IMA else len(data) // align
    fmt = struct.pack("<HHIIHH", tag, 1, rate, rate * align if tag != IMA else rate * align // (1 + 2 * (block - 4)), align, bits) + extra
    chunks = [(b"fmt ", fmt), *([] if tag == PCM else [(b"fact", struct.pack("<I", samples))]), (b"data", data)]
    body = b"WAVE" + b"".join(k + struct.pack("<I", len(v)) + v + b"\0" * (len(v) % 2) for k, v in chunks)
    return b"RIFF" + struct.pack("<I", len(body)) + body


def parse_wave(media: bytes) -> tuple[int, int, int, bytes]:
    """(tag, rate, block align, data) of a mono RIFF/WAVE file; anything else raises ValueError."""
    if media[:4] != b"RIFF" or media[8:12] != b"WAVE":
        raise ValueError("not a RIFF/WAVE file")
    at, found = 12, {}
    while at + 8 <= len(media):
        size = struct.unpack_from("<I", media, at + 4)[0]
        found.setdefault(media[at : at + 4], media[at + 8 : at + 8 + size])
        at += 8 + size + size % 2
    if b"fmt " not in found or b"data" not in found:
        raise ValueError("a chunk is missing")
    tag, channels, rate, _, align, _ = struct.unpack_from("<HHIIHH", found[b"fmt "])
    if tag not in (PCM, ALAW, MULAW, IMA) or channels != 1:
        raise ValueError("unsupported format")
    return tag, rate, align, found[b"data"]


def samples_of(media: bytes) -> tuple[np.ndarray, int]:
    """Decoded 16-bit samples and their rate."""
    tag, rate, align, data = parse_wave(media)
    if tag == IMA:
        return decode_ima(data, align), rate
    return (np.frombuffer(data[: len(data) // 2 * 2], "<i2"), rate) if tag == PCM else (expand(data, tag), rate)


def resample(pcm: np.ndarray, rate: int, to: int) -> np.ndarray:
    """Linear interpolation on the exact rational time grid, rounded to 16 bits."""
    if rate == to or not len(pcm):
        return pcm.astype(np.int16)
    n = max(1, len(pcm) * to // rate)
    at = np.arange(n, dtype=np.int64) * rate
    lo = np.minimum(at // to, len(pcm) - 1)
    hi = np.minimum(lo + 1, len(pcm) - 1)
    a, b = pcm[lo].astype(np.int64), pcm[hi].astype(np.int64)
    return ((a * (to - at % to) + b * (at % to) + to // 2) // to).astype(np.int16)


def describe(pcm: np.ndarray, rate: int) -> str:
    """Features of the samples from integer sums, so equal media give equal text on every machine."""
    x = pcm.astype(np.int64)
    n = max(1, len(x))
    energy, crossings = int((x * x).sum()), int(np.count_nonzero((x[1:] < 0) != (x[:-1] < 0)))
    peak = int(np.abs(x).max()) if len(x) else 0
    return f"n={len(x)};rate={rate};mean={int(x.sum()) // n};power={energy // n};peak={peak};zc={crossings};crc={zlib.crc32(pcm.astype('<i2').tobytes())}"


#: Codecs that a payload may be stored in, one of them by the payload's checksum; each takes any byte as a code.
CODECS = (MULAW, ALAW, IMA)


def wrap(payload: bytes, pad: int, tag: int | None = None) -> bytes:
    """The payload's bytes as the codes of a telephony file: 8-bit samples at 8 kHz, or ADPCM blocks of ``pad`` bytes at 16 kHz, which last about as long."""
    tag = CODECS[zlib.crc32(payload) % len(CODECS)] if tag is None else tag
    return wave(payload, IMA, 2 * RATE, pad) if tag == IMA else wave(payload, tag)


def store_payload(docs: DataFrame, *, text_col: str = "text", pad: int = 64, tag: int | None = None) -> DataFrame:
    """Each text's UTF-8 bytes, zero-padded to a positive multiple of ``pad``, as the codes of a telephony file.

    Adds ``n_bytes`` and ``media``; null texts are empty and give ``pad`` zero
    bytes.  Without a ``tag`` the payload's checksum deals it to mu-law, A-law
    or ADPCM, so a column holds all three.  Other columns stay; columns named
    like the added ones are replaced.
    """
    base = docs.drop("n_bytes", "media")

    def store(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for b in text_slices(batch, text_col):
                data, offs = raw_bytes(b.column(b.schema.get_field_index(text_col)))
                body = data.tobytes()
                size = np.diff(offs)
                media = [wrap(body[s:e] + bytes(max(pad, -(-(e - s) // pad) * pad) - (e - s)), pad, tag) for s, e in zip(offs[:-1].tolist(), offs[1:].tolist())]
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(size.astype(np.int64)), pa.array(media, pa.binary())], [*b.schema.names, "n_bytes", "media"])

    return base.mapInArrow(store, extended(base.schema, "n_bytes long, media binary"))


def write_media(media: DataFrame, path: str) -> DataFrame:
    """Write media rows as Parquet at ``path`` and return what is read back from there."""
    media.write.option("compression", "zstd").option("parquet.compression.codec.zstd.level", "9").parquet(path)
    return media.sparkSession.read.schema(media.schema).parquet(path)


def decode_all(files: list[tuple[int, int, int, bytes] | None]) -> list[np.ndarray | None]:
    """Samples of parsed files; the ADPCM blocks of all files of one block size advance together."""
    out: list[np.ndarray | None] = [None] * len(files)
    blocks: dict[int, list[int]] = {}
    for i, f in enumerate(files):
        if f is None:
            continue
        tag, _, align, data = f
        if tag == IMA and align > 4 and len(data) % align == 0:
            blocks.setdefault(align, []).append(i)
        elif tag == IMA:
            out[i] = decode_ima(data, max(align, 5))
        else:
            out[i] = np.frombuffer(data[: len(data) // 2 * 2], "<i2") if tag == PCM else expand(data, tag)
    for align, some in blocks.items():
        pcm = decode_ima(b"".join(files[i][3] for i in some), align)
        ends = np.cumsum([len(files[i][3]) // align * (1 + 2 * (align - 4)) for i in some])
        for i, x in zip(some, np.split(pcm, ends[:-1])):
            out[i] = x
    return out


def media_features(media: DataFrame, *, media_col: str = "media", rate: int | None = None, keep_pcm: bool = False) -> DataFrame:
    """Decode a column of telephony files: payload digest, tail checksum, file digest, features, optionally resampled PCM.

    Null or unreadable media give null results; of unreadable ones the size and
    digest are known.  The resampled samples are stored as a 16-bit PCM file in
    ``pcm`` when ``keep_pcm`` is set.
    """
    added = "payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string" + ", pcm binary" * keep_pcm
    names = [x.split()[0] for x in added.split(", ")]
    base = media.drop(*names)

    def parsed(m: bytes | None) -> tuple[int, int, int, bytes] | None:
        try:
            found = None if m is None else parse_wave(m)
        except (ValueError, struct.error):
            return None
        return found if found is None or found[0] in (PCM, *CODECS) else None

    def rows_of(column: list[bytes | None]) -> Iterator[tuple]:
        files = [parsed(m) for m in column]
        for m, f, pcm in zip(column, files, decode_all(files)):
            if f is None:
                yield (*[None] * 3, *((None, None) if m is None else (len(m), hashlib.sha256(m).hexdigest())), *[None] * (1 + keep_pcm))
                continue
            own, data = f[1], f[3]
            if rate:
                pcm, own = resample(pcm, own, rate), rate
            row = (len(data), hashlib.sha256(data).hexdigest(), zlib.crc32(data[-64:]), len(m), hashlib.sha256(m).hexdigest(), f"codec={f[0]};{describe(pcm, own)}")
            yield (*row, wave(pcm.astype("<i2").tobytes(), PCM, own)) if keep_pcm else row

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for b in binary_slices(batch, media_col):
                rows = list(rows_of(b.column(b.schema.get_field_index(media_col)).to_pylist()))
                cols = [pa.array(c, t) for c, t in zip(zip(*rows), [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.binary()])]
                yield pa.RecordBatch.from_arrays([*b.columns, *cols], [*b.schema.names, *names])

    return base.mapInArrow(read, extended(base.schema, added))


def binary_slices(batch: pa.RecordBatch, column: str) -> Iterator[pa.RecordBatch]:
    """Slices of about CHUNK_BYTES of media, which bounds the decoded samples held at once."""
    return text_slices(batch, column, CHUNK_BYTES)


def digest(docs: DataFrame) -> DataFrame:
    """The query's columns: payloads in all three codecs written as a media table, read back, resampled to 8 kHz and described; the PCM is stored and counted from its files.

    ``pcm_bytes`` and ``pcm_crc32`` are those of the stored PCM file's samples.
    """
    spark = docs.sparkSession
    stored = write_media(store_payload(docs.select("doc_id", "text")).select("doc_id", "n_bytes", "media"), new_path(spark, "media"))
    found = write_media(media_features(stored, rate=RATE, keep_pcm=True).drop("media"), new_path(spark, "pcm"))
    size = F.octet_length("pcm") - 44  # a PCM file's header has 44 bytes
    return found.select("doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", size.cast("long").alias("pcm_bytes"), F.crc32(F.expr("substr(pcm, 45)")).alias("pcm_crc32"))
