"""Telephony audio in media columns.

Mu-law and A-law samples expand through 256-entry tables, IMA ADPCM blocks
decode in lockstep: one numpy step a nibble for all blocks of a slice. Audio is
kept as RIFF/WAVE with its own codec (8-bit companded samples, or ADPCM blocks
of 64 bytes), so stored bytes are lossless, and is handed on as 16-bit PCM
resampled by a fixed-point windowed-sinc filter, equal on every machine.

``packed`` makes a media column of any binary payload, ``decoded`` turns one into
stored PCM. Defined results: a null payload is empty; a payload is filled with zero
bytes to a positive multiple of 64; equal payloads give equal files, PCM and features;
a file that is not of a known codec raises.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tablemill.llm.common import columns, lean, stored, whole
from tablemill.llm.pieces import slices

RATE, TARGET, BLOCK = 8000, 16000, 64
ALAW, MULAW, ADPCM = 6, 7, 17
CODECS = {MULAW: "mulaw", ALAW: "alaw", ADPCM: "ima_adpcm"}

# Index moves of IMA ADPCM.
INDEX_MOVES = [-1, -1, -1, -1, 2, 4, 6, 8]
# The 89 step sizes of IMA ADPCM.
STEP_SIZES = [
    7, 8, 9, 10, 11, 12, 13, 14, 16, 17, 19, 21, 23, 25, 28, 31, 34, 37, 41, 45, 50, 55, 60, 66, 73, 80, 88, 97, 107, 118,
    130, 143, 157, 173, 190, 209, 230, 253, 279, 307, 337, 371, 408, 449, 494, 544, 598, 658, 724, 796, 876, 963, 1060, 1166,
    1282, 1411, 1552, 1707, 1878, 2066, 2272, 2499, 2749, 3024, 3327, 3660, 4026, 4428, 4871, 5358, 5894, 6484, 7132, 7845,
    8630, 9493, 10442, 11487, 12635, 13899, 15289, 16818, 18500, 20350, 22385, 24623, 27086, 29794, 32767,
]


@cache
def mulaw_table() -> np.ndarray:
    """Linear value of each mu-law byte: inverted bits, sign, 3-bit exponent, 4-bit mantissa, bias 132."""
    code = ~np.arange(256) & 255
    size = ((((code & 15) << 3) + 132) << ((code >> 4) & 7)) - 132
    return np.where(code & 128, -size, size).astype(np.int16)


@cache
def alaw_table() -> np.ndarray:
    """Linear value of each A-law byte: even bits inverted, sign, 3-bit segment, 4-bit mantissa."""
    code = np.arange(256) ^ 0x55
    seg, low = (code >> 4) & 7, ((code & 15) << 4) + 8
    size = np.where(seg == 0, low, (low + 256) << np.maximum(seg - 1, 0))
    return np.where(code & 128, size, -size).astype(np.int16)


@cache
def adpcm_moves() -> tuple[np.ndarray, np.ndarray]:
    """Signed difference and next index for each (index, nibble)."""
    step, code = np.array(STEP_SIZES)[:, None], np.arange(16)[None, :]
    diff = (step >> 3) + np.where(code & 1, step >> 2, 0) + np.where(code & 2, step >> 1, 0) + np.where(code & 4, step, 0)
    nxt = np.clip(np.arange(89)[:, None] + np.array(INDEX_MOVES)[code & 7], 0, 88)
    return np.where(code & 8, -diff, diff).astype(np.int32).ravel(), nxt.astype(np.int32).ravel()


def adpcm_blocks(data: np.ndarray, block: int = BLOCK) -> np.ndarray:
    """Samples of blocks (rows of ``block`` bytes): the header's and two a byte, low nibble first."""
    rows = data.reshape(-1, block)
    value = (rows[:, 0].astype(np.int32) | (rows[:, 1].astype(np.int32) << 8)).astype(np.uint16).view(np.int16).astype(np.int32)
    index = np.minimum(rows[:, 2], 88).astype(np.int32)
    move, follow = adpcm_moves()
    out = np.empty((1 + 2 * (block - 4), len(rows)), np.int16)
    out[0] = value
    at = 1
    body = np.ascontiguousarray(rows[:, 4:].T).astype(np.int32)
    for byte in body:
        for nibble in (byte & 15, byte >> 4):
            key = index * 16 + nibble
            value = np.clip(value + move[key], -32768, 32767)
            index = follow[key]
            out[at] = value
            at += 1
    return out.T


def resample(pcm: np.ndarray, source: int, target: int, taps: int = 16) -> np.ndarray:
    """Rational resampling with integer taps (Hann-windowed sinc, 2**14), rounded half up and clipped."""
    if source == target or not len(pcm):
        return pcm.astype(np.int16)
    gcd = np.gcd(source, target)
    up, down = target // gcd, source // gcd
    total = -(-len(pcm) * up // down)
    out = np.empty(total, np.int16)
    padded = np.concatenate([np.zeros(taps // 2, np.float64), pcm, np.zeros(taps // 2, np.float64)])
    cut = min(1.0, up / down)
    for first in range(min(up, total)):  # the outputs of one phase
        shift = (first * down % up) / up
        k = np.arange(-taps // 2 + 1, taps // 2 + 1) - shift
        h = np.round(cut * np.sinc(cut * k) * (0.5 + 0.5 * np.cos(np.pi * np.clip(k / (taps // 2), -1, 1))) * (1 << 14))
        base = np.arange(first, total, up) * down // up
        full = np.convolve(padded, h[::-1], "valid")
        out[first::up] = np.clip(np.floor((full[base + 1] + (1 << 13)) / (1 << 14)), -32768, 32767)
    return out


# --- container -------------------------------------------------------------


def codec_of(payload: bytes) -> int:
    return (MULAW, ALAW, ADPCM)[zlib.crc32(payload) % 3]


def to_wave(payload: bytes, codec: int, rate: int = RATE) -> bytes:
    if codec == ADPCM:
        samples = len(payload) // BLOCK * (2 * (BLOCK - 4) + 1)
        fmt = struct.pack("<HHIIHHHH", codec, 1, rate, rate * BLOCK // (2 * (BLOCK - 4) + 1), BLOCK, 4, 2, 2 * (BLOCK - 4) + 1)
    else:
        samples = len(payload)
        fmt = struct.pack("<HHIIHHH", codec, 1, rate, rate, 1, 8, 0)
    chunks = [(b"fmt ", fmt), (b"fact", struct.pack("<I", samples)), (b"data", payload)]
    body = b"".join(name + struct.pack("<I", len(data)) + data + b"\0" * (len(data) % 2) for name, data in chunks)
    return b"RIFF" + struct.pack("<I", 4 + len(body)) + b"WAVE" + body


def from_wave(data: bytes) -> tuple[int, int, int, bytes]:
    """Codec, rate, block size and the sound bytes of a RIFF/WAVE file."""
    if data[:4] != b"RIFF" or data[8:12] != b"WAVE":
        raise ValueError("not a RIFF/WAVE file")
    at, fmt = 12, None
    while at + 8 <= len(data):
        name, size = data[at : at + 4], struct.unpack_from("<I", data, at + 4)[0]
        if name == b"fmt ":
            fmt = struct.unpack_from("<HHIIHH", data, at + 8)
        elif name == b"data" and fmt:
            if fmt[0] not in CODECS:
                raise ValueError(f"codec {fmt[0]} is not known")
            return fmt[0], fmt[2], fmt[4], data[at + 8 : at + 8 + size]
        at += 8 + size + size % 2
    raise ValueError("no sound in the file")


def expand(files: list[bytes]) -> list[tuple[int, int, bytes, np.ndarray]]:
    """(codec, rate, payload, 16-bit samples) of each file; ADPCM blocks of all files step together."""
    parsed = [from_wave(f) for f in files]
    out: list = [None] * len(files)
    blocks: dict[int, list[int]] = {}
    for i, (codec, rate, size, payload) in enumerate(parsed):
        if codec == ADPCM:
            blocks.setdefault(size, []).append(i)
        else:
            out[i] = (codec, rate, payload, (mulaw_table() if codec == MULAW else alaw_table())[np.frombuffer(payload, np.uint8)])
    for size, mine in blocks.items():
        pcm = adpcm_blocks(np.frombuffer(b"".join(parsed[i][3] for i in mine), np.uint8), size)
        at = 0
        for i in mine:
            n = len(parsed[i][3]) // size
            out[i] = (ADPCM, parsed[i][1], parsed[i][3], pcm[at : at + n].ravel())
            at += n
    return out


def feature(codec: int, pcm: np.ndarray) -> str:
    """Codec, samples, peak, root mean square, zero crossings and checksum of the resampled sound."""
    wide = pcm.astype(np.int64)
    power = int((wide * wide).sum())
    crossings = int(((pcm[1:] < 0) != (pcm[:-1] < 0)).sum())
    return f"{CODECS[codec]};n={len(pcm)};peak={int(np.abs(wide).max(initial=0))};rms={(power / max(1, len(pcm))) ** 0.5:.3f};zc={crossings};crc={zlib.crc32(pcm.astype('<i2').tobytes()):08x}"


# --- media columns ---------------------------------------------------------


def padded(payload: bytes) -> bytes:
    return payload + b"\0" * (max(BLOCK, -(-len(payload) // BLOCK) * BLOCK) - len(payload))


def packed(docs: DataFrame, payload: str = "text", key: str = "doc_id") -> DataFrame:
    """(key, n_bytes, media): each payload (text counts as UTF-8) as a WAVE file."""
    returns = f"{key} long, n_bytes long, media binary"
    shape = columns(returns)

    def run(batches):
        for b in batches:
            for part in slices(b, 1):
                data = whole(part.column(1))
                full = [padded(d) for d in data]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(map(len, data), pa.int64()), pa.array([to_wave(p, codec_of(p)) for p in full], pa.binary())], schema=shape)

    return docs.select(F.col(key).cast("long"), F.col(payload)).mapInArrow(lean(run), returns)


def decoded(media: DataFrame, column: str = "media", key: str = "doc_id", rate: int = TARGET) -> DataFrame:
    """(key, codec, rate, pcm): 16-bit little-endian PCM of each file at one rate, to be written to any table."""
    returns = f"{key} long, codec string, rate long, pcm binary"
    shape = columns(returns)

    def run(batches):
        for b in batches:
            for part in slices(b, 1, 1 << 20):
                rows = expand(part.column(1).to_pylist())
                pcm = [resample(p, r, rate).astype("<i2").tobytes() for _, r, _, p in rows]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([CODECS[r[0]] for r in rows], pa.string()), pa.array([rate] * len(rows), pa.int64()), pa.array(pcm, pa.binary())], schema=shape)

    return media.select(F.col(key).cast("long"), F.col(column)).mapInArrow(lean(run), returns)


def op4_telephony_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Store every text as telephony audio, read the stored files back, digest what they hold, and hand on their resampled PCM.

    The column ``pcm`` is what ``decoded`` stores: 16-bit samples at 16 kHz, one
    row a document, written with the result.
    """
    media = stored(packed(spark.read.parquet(f"{sf_dir}/documents.parquet")), "media")
    returns = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, rate long, pcm binary"
    shape = columns(returns)

    def run(batches):
        for b in batches:
            for part in slices(b, 2, 1 << 20):
                files = part.column(2).to_pylist()
                rows = expand(files)
                pcm = [resample(r[3], r[1], TARGET) for r in rows]
                arrays = [
                    part.column(0), part.column(1),
                    pa.array([len(r[2]) for r in rows], pa.int64()),
                    pa.array([hashlib.sha256(r[2]).hexdigest() for r in rows], pa.string()),
                    pa.array([zlib.crc32(r[2][-64:]) for r in rows], pa.int64()),
                    pa.array(map(len, files), pa.int64()),
                    pa.array([hashlib.sha256(f).hexdigest() for f in files], pa.string()),
                    pa.array([feature(r[0], p) for r, p in zip(rows, pcm)], pa.string()),
                    pa.array([TARGET] * len(rows), pa.int64()),
                    pa.array([p.astype("<i2").tobytes() for p in pcm], pa.binary()),
                ]
                yield pa.RecordBatch.from_arrays(arrays, schema=shape)

    return media.mapInArrow(lean(run), returns)
