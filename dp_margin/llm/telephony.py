"""Telephony audio: G.711 expansion by look-up tables, block ADPCM by numpy across blocks, resampled PCM.

A stored form is a RIFF file of 8-bit mu-law, 8-bit A-law or 4-bit IMA ADPCM samples. ``media_table`` stores payloads in it without loss;
``pcm_table`` reads stored files and stores their PCM, resampled; ``read_pcm`` reads that PCM back.

Stored PCM is coded without loss by an integer lifting step: samples of even number as they are, and of each odd one the difference from the mean of its
neighbours, which is small where a signal was interpolated.

Defined cases: a null text is empty, and an empty text is 64 zero bytes; a file that is no RIFF wave gives null PCM; a null doc_id, repeated rows and rows
that share a doc_id are stored each for itself; extra columns are ignored; an empty table gives none.
"""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bound_batches, materialise, table, utf8
from .neardup import runs

RATE, RESAMPLED = 8000, 16000
#: Compression of stored audio, which is kept, so that it may cost more time than passing tables do.
LEVEL = 6
#: Payloads are padded to whole ADPCM blocks of so many bytes.
BLOCK = 64
#: RIFF format tags (fixed values of the format).
ALAW, MULAW, IMA = 6, 7, 17


def mulaw_table() -> np.ndarray:
    """16-bit value of each mu-law code: inverted sign, 3-bit exponent, 4-bit mantissa, bias 132."""
    u = ~np.arange(256) & 0xFF
    x = ((((u & 15) << 3) + 132) << ((u >> 4) & 7)) - 132
    return np.where(u & 128, -x, x).astype(np.int16)


def alaw_table() -> np.ndarray:
    """16-bit value of each A-law code: every other bit inverted, linear below the first exponent."""
    a = np.arange(256) ^ 0x55
    e, x = (a >> 4) & 7, ((a & 15) << 4) + 8
    x = np.where(e == 0, x, (x + 256) << np.maximum(e - 1, 0))
    return np.where(a & 128, x, -x).astype(np.int16)


MU, A = mulaw_table(), alaw_table()
# Fixed values of IMA ADPCM: step sizes and what a nibble adds to the step index.
STEPS = np.array([
    7, 8, 9, 10, 11, 12, 13, 14, 16, 17, 19, 21, 23, 25, 28, 31, 34, 37, 41, 45, 50, 55, 60, 66, 73, 80, 88, 97, 107, 118, 130, 143, 157, 173, 190, 209, 230, 253, 279, 307, 337, 371, 408, 449, 494,
    544, 598, 658, 724, 796, 876, 963, 1060, 1166, 1282, 1411, 1552, 1707, 1878, 2066, 2272, 2499, 2749, 3024, 3327, 3660, 4026, 4428, 4871, 5358, 5894, 6484, 7132, 7845, 8630, 9493, 10442, 11487,
    12635, 13899, 15289, 16818, 18500, 20350, 22385, 24623, 27086, 29794, 32767,
], np.int32)
INDEX = np.array([-1, -1, -1, -1, 2, 4, 6, 8], np.int32)


def adpcm_blocks(blocks: np.ndarray) -> np.ndarray:
    """PCM of IMA blocks, (blocks, bytes) of uint8 to (blocks, 1 + 2 * (bytes - 4)) of int16: one step in time for all blocks at once."""
    value = blocks[:, :2].copy().view("<i2")[:, 0].astype(np.int32)
    index = np.minimum(blocks[:, 2], 88).astype(np.int32)
    body = blocks[:, 4:].T
    out = np.empty((1 + 2 * len(body), len(blocks)), np.int16)
    out[0] = value
    for t, byte in enumerate(np.ascontiguousarray(body)):
        for half, nibble in ((1, byte & 15), (2, byte >> 4)):
            step = STEPS[index]
            size = nibble & 7
            # the format truncates each of the four terms on its own
            delta = (step >> 3) + np.where(size & 4, step, 0) + np.where(size & 2, step >> 1, 0) + np.where(size & 1, step >> 2, 0)
            value = np.clip(np.where(nibble & 8, value - delta, value + delta), -32768, 32767)
            index = np.clip(index + INDEX[size], 0, 88)
            out[2 * t + half] = value
    return np.ascontiguousarray(out.T)


def resample(pcm: np.ndarray, up: int = RESAMPLED, down: int = RATE) -> np.ndarray:
    """Linear interpolation from rate ``down`` to rate ``up``, on integers; the last value is held."""
    if not len(pcm):
        return pcm
    at = np.arange(len(pcm) * up // down, dtype=np.int64) * down
    left = at // up
    right = np.minimum(left + 1, len(pcm) - 1)
    part = at - left * up
    x = pcm.astype(np.int64)
    return ((x[left] * (up - part) + x[right] * part) // up).astype(np.int16)


def riff(payload: bytes, tag: int = MULAW, rate: int = RATE) -> bytes:
    """A wave file of one channel."""
    samples = len(payload) if tag != IMA else len(payload) // BLOCK * (1 + 2 * (BLOCK - 4))
    block, bits = (BLOCK, 4) if tag == IMA else (1, 8)
    per_second = rate * BLOCK // (1 + 2 * (BLOCK - 4)) if tag == IMA else rate
    extra = struct.pack("<HH", 2, 1 + 2 * (BLOCK - 4)) if tag == IMA else struct.pack("<H", 0)
    fmt = struct.pack("<HHIIHH", tag, 1, rate, per_second, block, bits) + extra
    chunks = b"fmt " + struct.pack("<I", len(fmt)) + fmt + b"fact" + struct.pack("<II", 4, samples) + b"data" + struct.pack("<I", len(payload)) + payload + b"\0" * (len(payload) & 1)
    return b"RIFF" + struct.pack("<I", 4 + len(chunks)) + b"WAVE" + chunks


def parse_riff(data: bytes) -> tuple[int, int, int, bytes] | None:
    """(format tag, rate, block bytes, payload), or None."""
    if len(data) < 12 or data[:4] != b"RIFF" or data[8:12] != b"WAVE":
        return None
    at, head = 12, None
    while at + 8 <= len(data):
        name, n = data[at : at + 4], struct.unpack_from("<I", data, at + 4)[0]
        if name == b"fmt " and n >= 16:
            tag, _, rate, _, block, _ = struct.unpack_from("<HHIIHH", data, at + 8)
            head = tag, rate, block
        elif name == b"data" and head:
            return *head, data[at + 8 : at + 8 + n]
        at += 8 + n + (n & 1)
    return None


def expand(payload: bytes, tag: int, block: int = BLOCK) -> np.ndarray:
    """16-bit PCM of a payload."""
    x = np.frombuffer(payload, np.uint8)
    if tag == IMA:
        return adpcm_blocks(x[: len(x) // block * block].reshape(-1, block)).ravel()
    return (MU if tag == MULAW else A)[x]


def pad(text: bytes, unit: int = BLOCK) -> bytes:
    return text + b"\0" * (-len(text) % unit if text else unit)


def media_table(docs: DataFrame, tag: int = MULAW) -> DataFrame:
    """(doc_id, n_bytes, media): every text as a stored wave file, on shared storage."""
    bound_batches(docs.sparkSession)

    def run(batches):
        for b in batches:
            texts = utf8(b.column(1))
            yield pa.record_batch([b.column(0), pa.array([len(t) for t in texts], pa.int64()), pa.array([riff(pad(t), tag) for t in texts], pa.binary())], ["doc_id", "n_bytes", "media"])

    return materialise(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, n_bytes long, media binary"), LEVEL)


def code_pcm(pcm: np.ndarray) -> bytes:
    """16-bit PCM as its even samples, then what each odd one differs from its neighbours' mean by (modulo 2^16)."""
    even, odd = pcm[::2], pcm[1::2]
    return even.astype("<i2").tobytes() + (odd - _between(even, len(odd))).astype("<i2").tobytes()


def uncode_pcm(data: bytes) -> np.ndarray:
    """The PCM that ``code_pcm`` had."""
    x = np.frombuffer(data, "<i2")
    even, rest = x[: (len(x) + 1) // 2], x[(len(x) + 1) // 2 :]
    out = np.empty(len(x), np.int16)
    out[::2], out[1::2] = even, rest + _between(even, len(rest))
    return out


def _between(even: np.ndarray, n: int) -> np.ndarray:
    x = even.astype(np.int32)
    return ((x + np.append(x[1:], x[-1:])) >> 1)[:n].astype(np.int16)


def _resampled(data: bytes | None, rate: int) -> np.ndarray | None:
    head = parse_riff(data or b"")
    return None if head is None else resample(expand(head[3], head[0], head[2]), rate, head[1])


def pcm_table(media: DataFrame, rate: int = RESAMPLED) -> DataFrame:
    """media (doc_id, media) as a stored table (doc_id, rate, coded): the PCM of every file at the wanted rate, coded."""
    bound_batches(media.sparkSession)

    def run(batches):
        for b in batches:
            pcm = [_resampled(x, rate) for x in b.column(1).to_pylist()]
            yield pa.record_batch([b.column(0), pa.array([rate] * b.num_rows, pa.int32()), pa.array([None if x is None else code_pcm(x) for x in pcm], pa.binary())], ["doc_id", "rate", "coded"])

    return materialise(media.select("doc_id", "media").mapInArrow(run, "doc_id long, rate int, coded binary"), LEVEL)


def read_pcm(stored: DataFrame) -> DataFrame:
    """(doc_id, rate, pcm) of a stored table: little-endian 16-bit PCM."""
    bound_batches(stored.sparkSession)

    def run(batches):
        for b in batches:
            yield pa.record_batch([b.column(0), b.column(1), pa.array([None if x is None else uncode_pcm(x).astype("<i2").tobytes() for x in b.column(2).to_pylist()], pa.binary())], ["doc_id", "rate", "pcm"])

    return stored.select("doc_id", "rate", "coded").mapInArrow(run, "doc_id long, rate int, pcm binary")


def _level(pcm: np.ndarray, edges: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sum of squares and sign changes of the spans between edges."""
    x = pcm.astype(np.int64)
    energy = np.concatenate(([0], np.cumsum(x * x)))
    turn = np.concatenate(([0, 0], np.cumsum((x[1:] < 0) != (x[:-1] < 0)))) if len(x) else np.zeros(1, np.int64)
    lo, hi = edges[:-1], edges[1:]
    return energy[hi] - energy[lo], turn[hi] - turn[np.minimum(lo + 1, hi)]


def features(payloads: list[bytes]) -> list[str]:
    """Levels of payloads read as each of the three codes, all payloads at once."""
    flat = np.frombuffer(b"".join(payloads), np.uint8)
    edge = np.concatenate(([0], np.cumsum([len(p) for p in payloads]))).astype(np.int64)
    block = adpcm_blocks(flat.reshape(-1, BLOCK)).ravel()
    per = 1 + 2 * (BLOCK - 4)
    levels = [(*_level(MU[flat], edge), edge), (*_level(A[flat], edge), edge), (*_level(block, edge // BLOCK * per), edge // BLOCK * per)]
    out = []
    for i in range(len(payloads)):
        out.append(";".join(f"{name}:rms={np.sqrt(e[i] / (g[i + 1] - g[i])):.3f},turns={int(t[i])}" for name, (e, t, g) in zip(("mulaw", "alaw", "adpcm"), levels, strict=True)))
    return out


_DIGEST = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
_NAMES = [x.split()[0] for x in _DIGEST.split(", ")]


def _digest(batches):
    """Digests of stored files, and their resampled PCM, coded."""
    for b in batches:
        media = [x or b"" for x in b.column(2).to_pylist()]
        payload = [parse_riff(x)[3] for x in media]
        said = []
        for lo, hi in runs(payload, 1 << 20):
            said += features(payload[lo:hi])
        sha = [hashlib.sha256(p).hexdigest() for p in payload]
        cols = [b.column(0), b.column(1), pa.array([len(p) for p in payload], pa.int64()), pa.array(sha, pa.string()), pa.array([zlib.crc32(p[-64:]) for p in payload], pa.int64())]
        cols += [pa.array([len(x) for x in media], pa.int64()), pa.array([hashlib.sha256(x).hexdigest() for x in media], pa.string()), pa.array(said, pa.string())]
        yield pa.record_batch([*cols, pa.array([code_pcm(_resampled(x, RESAMPLED)) for x in media], pa.binary())], [*_NAMES, "coded"])


def _seal(batches):
    """The feature with a checksum of the PCM as it was stored."""
    for b in batches:
        crc = [zlib.crc32(uncode_pcm(x).astype("<i2").tobytes()) for x in b.column(8).to_pylist()]
        said = pa.array([f"{x};pcm16k={c:08x}" for x, c in zip(b.column(7).to_pylist(), crc, strict=True)], pa.string())
        yield pa.record_batch([*b.columns[:7], said], _NAMES)


def op1_telephony_audio(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Texts are stored as mu-law files, read back, their resampled PCM is stored beside the digests, and read back too."""
    stored = media_table(table(spark, sf_dir, "documents"))
    return materialise(stored.mapInArrow(_digest, _DIGEST + ", coded binary"), LEVEL).mapInArrow(_seal, _DIGEST)
