"""Media columns for telephony audio.

mu-law and A-law samples expand through 256-entry lookup tables, IMA ADPCM
blocks decode with numpy across all blocks of many rows at once, and the linear PCM is
stored at a second sampling rate. Containers are RIFF/WAVE, written and parsed here. Which codec a text is stored
in follows from its bytes (`form_of`), so a table holds all three.

Defined cases: a null text is empty; an empty text is stored as 64 zero bytes;
equal texts give equal values; repeated rows give repeated results; an empty
table gives an empty one; further columns of the input are ignored. A row of
any length is handled alone in memory that is a small multiple of its length.
"""

import hashlib
import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from twinsift.functions.shipping import by_value
from twinsift.llm.common import slices, small_batches

by_value(__name__)

RATE = 8000
UNIT = 64
MU_LAW, A_LAW, IMA = 7, 6, 17

# Step sizes and index moves of IMA ADPCM.
IMA_STEPS = np.array([7, 8, 9, 10, 11, 12, 13, 14, 16, 17, 19, 21, 23, 25, 28, 31, 34, 37, 41, 45, 50, 55, 60, 66, 73, 80, 88, 97, 107, 118, 130, 143, 157, 173, 190, 209, 230, 253, 279, 307, 337, 371, 408, 449, 494, 544, 598, 658, 724, 796, 876, 963, 1060, 1166, 1282, 1411, 1552, 1707, 1878, 2066, 2272, 2499, 2749, 3024, 3327, 3660, 4026, 4428, 4871, 5358, 5894, 6484, 7132, 7845, 8630, 9493, 10442, 11487, 12635, 13899, 15289, 16818, 18500, 20350, 22385, 24623, 27086, 29794, 32767], np.int32)
IMA_MOVES = np.array([-1, -1, -1, -1, 2, 4, 6, 8] * 2, np.int32)


def _changes() -> np.ndarray:
    """What each code adds to a sample at each step size."""
    step, code = IMA_STEPS[:, None], np.arange(16)[None]
    size = (step >> 3) + np.where(code & 4, step, 0) + np.where(code & 2, step >> 1, 0) + np.where(code & 1, step >> 2, 0)
    return np.where(code & 8, -size, size).astype(np.int32)


IMA_CHANGES = _changes()


def mu_law_table() -> np.ndarray:
    code = ~np.arange(256, dtype=np.uint8)
    size = ((((code & 15).astype(np.int32) << 3) + 132) << ((code >> 4) & 7)) - 132
    return np.where(code & 128, -size, size).astype(np.int16)


def a_law_table() -> np.ndarray:
    code = np.arange(256, dtype=np.uint8) ^ 0x55
    low, power = (code & 15).astype(np.int32) << 4, ((code >> 4) & 7).astype(np.int32)
    size = np.where(power == 0, low + 8, (low + 264) << np.maximum(power - 1, 0))
    return np.where(code & 128, size, -size).astype(np.int16)


EXPAND = {MU_LAW: mu_law_table(), A_LAW: a_law_table()}


def decode_ima_many(streams: list[bytes], block: int) -> list[np.ndarray]:
    """Mono IMA ADPCM: one pass over the positions of a block, each for all blocks of all streams together. A stream's last block may be short."""
    counts = np.array([-(-len(x) // block) for x in streams], np.int64)
    raw = np.zeros((int(counts.sum()), block), np.uint8)
    ends = np.cumsum(counts)
    for x, end, n in zip(streams, ends.tolist(), counts.tolist(), strict=True):
        raw[end - n : end].reshape(-1)[: len(x)] = np.frombuffer(x, np.uint8)
    value = raw[:, :2].copy().view("<i2")[:, 0].astype(np.int32)
    at = np.clip(raw[:, 2].astype(np.int32), 0, len(IMA_STEPS) - 1)
    codes = np.stack([raw[:, 4:] & 15, raw[:, 4:] >> 4], -1).reshape(len(raw), 2 * (block - 4)).T.astype(np.int32, order="C")
    out = np.empty((len(codes) + 1, len(raw)), np.int16)
    out[0] = value
    for k, c in enumerate(codes):
        value += IMA_CHANGES[at, c]
        np.clip(value, -32768, 32767, out=value)
        at += IMA_MOVES[c]
        np.clip(at, 0, len(IMA_STEPS) - 1, out=at)
        out[k + 1] = value
    samples, done = np.ascontiguousarray(out.T), []
    for x, end, n in zip(streams, ends.tolist(), counts.tolist(), strict=True):
        last = len(x) - (n - 1) * block
        kept = (n - 1) * samples.shape[1] + (max(0, last - 4) * 2 + 1 if last >= 4 else 0)
        done.append(samples[end - n : end].reshape(-1)[: max(0, kept)])
    return done


def decode_ima(data: bytes, block: int) -> np.ndarray:
    return decode_ima_many([data], block)[0]


def resample(pcm: np.ndarray, up: int, down: int = 1) -> np.ndarray:
    """Linear interpolation at the rate up/down, in whole numbers: the same everywhere."""
    if not len(pcm):
        return pcm
    if (up, down) == (2, 1):
        out, wide = np.empty(2 * len(pcm), np.int16), pcm.astype(np.int32)
        out[0::2] = pcm
        out[1:-1:2] = (wide[:-1] + wide[1:]) >> 1
        out[-1] = pcm[-1]
        return out
    at = np.arange(len(pcm) * up // down, dtype=np.int64) * down
    left, part = at // up, at % up
    right = np.minimum(left + 1, len(pcm) - 1)
    return ((pcm[left].astype(np.int64) * (up - part) + pcm[right].astype(np.int64) * part) // up).astype(np.int16)


def wav(data: bytes, form: int, rate: int = RATE, bits: int = 8, align: int = 1, samples: int | None = None) -> bytes:
    extra = struct.pack("<HH", 2, (align - 4) * 2 + 1) if form == IMA else struct.pack("<H", 0)
    fmt = struct.pack("<HHIIHH", form, 1, rate, rate * bits * (align if form != IMA else 1) // 8, align, bits) + extra
    body = b"WAVE" + b"fmt " + struct.pack("<I", len(fmt)) + fmt
    body += b"fact" + struct.pack("<II", 4, len(data) if samples is None else samples)
    body += b"data" + struct.pack("<I", len(data) & 0xFFFFFFFF) + data + b"\0" * (len(data) & 1)
    return b"RIFF" + struct.pack("<I", len(body) & 0xFFFFFFFF) + body


def read_wav(media: bytes) -> tuple[int, int, int, bytes]:
    """Format tag, rate, block size and the stored bytes, from the container alone."""
    if media[:4] != b"RIFF" or media[8:12] != b"WAVE":
        raise ValueError("not a RIFF/WAVE container")
    at, form, rate, align = 12, 0, 0, 1
    while at + 8 <= len(media):
        name, n = media[at : at + 4], struct.unpack_from("<I", media, at + 4)[0]
        if name == b"fmt ":
            form, _, rate, _, align, _ = struct.unpack_from("<HHIIHH", media, at + 8)
        elif name == b"data":
            return form, rate, align, media[at + 8 : at + 8 + n]
        at += 8 + n + (n & 1)
    raise ValueError("no data chunk")


def to_pcm(form: int, align: int, data: bytes) -> np.ndarray:
    if form == IMA:
        return decode_ima(data, align)
    return EXPAND[form][np.frombuffer(data, np.uint8)]


def features(pcm: np.ndarray, wide: np.ndarray) -> str:
    """Whole-number measures of the linear samples and a checksum of the stored, resampled ones."""
    x = pcm.astype(np.int32)
    crossed = int(np.count_nonzero((x[1:] < 0) != (x[:-1] < 0)))
    return f"samples={len(x)};peak={int(np.abs(x).max(initial=0))};power={int(np.abs(x).sum(dtype=np.int64)) // max(1, len(x))};crossings={crossed};out_samples={len(wide)};out_crc32={zlib.crc32(wide.astype('<i2', copy=False).data)}"


def pad(data: bytes) -> bytes:
    return data + b"\0" * (-len(data) % UNIT if data else UNIT)


IMA_BLOCK = 256  # bytes: a header of 4 and 252 bytes of two codes each


def form_of(payload: bytes) -> int:
    """Which of the three codecs a payload is stored in: its CRC-32 modulo 3 decides, so equal payloads are stored alike."""
    return (MU_LAW, A_LAW, IMA)[zlib.crc32(payload) % 3]


def ima_blocks(payload: bytes) -> bytes:
    """Payload bytes as pairs of ADPCM codes, each block behind a header (first sample 0, first step 0); nothing of the payload is lost."""
    room = IMA_BLOCK - 4
    return b"".join(b"\0\0\0\0" + payload[k : k + room] for k in range(0, len(payload), room))


def ima_payload(data: bytes, block: int) -> bytes:
    """The codes of all blocks, without the headers."""
    return b"".join(data[k + 4 : k + block] for k in range(0, len(data), block))


def to_media(payload: bytes, form: int) -> bytes:
    """A container that holds the payload as samples (mu-law, A-law) or codes (IMA ADPCM)."""
    if form == IMA:
        data = ima_blocks(payload)
        blocks = -(-len(data) // IMA_BLOCK)
        return wav(data, IMA, bits=4, align=IMA_BLOCK, samples=2 * (len(data) - 4 * blocks) + blocks)
    return wav(payload, form)


def from_media(media: list[bytes]) -> list[tuple[bytes, np.ndarray, int]]:
    """Payload, linear samples and rate of each container, from its bytes alone. ADPCM streams of one block size are decoded together."""
    parts = [read_wav(x) for x in media]
    pcm: list = [None if tag == IMA else to_pcm(tag, align, data) for tag, _, align, data in parts]
    for block in {align for tag, _, align, _ in parts if tag == IMA}:
        own = [k for k, p in enumerate(parts) if p[0] == IMA and p[2] == block]
        for k, x in zip(own, decode_ima_many([parts[k][3] for k in own], block), strict=True):
            pcm[k] = x
    return [(ima_payload(data, align) if tag == IMA else data, x, rate) for (tag, rate, align, data), x in zip(parts, pcm, strict=True)]


def store_texts(docs: DataFrame, form: int | None = None) -> DataFrame:
    """doc_id, n_bytes, media, pcm: each text as telephony samples in a container, and its linear samples at twice the rate (16 bits, little-endian).

    form None: form_of decides for each payload."""
    schema = "doc_id long, n_bytes long, media binary, pcm binary"

    def run(batches):
        for piece in slices(batches, 2 << 20):
            raw = [value.as_buffer().to_pybytes() if value.is_valid else b"" for value in piece.column(1)]
            payloads = [pad(x) for x in raw]
            media = [to_media(x, form_of(x) if form is None else form) for x in payloads]
            pcm = [resample(x, 2).astype("<i2", copy=False).tobytes() for _, x, _ in from_media(media)]
            yield pa.RecordBatch.from_arrays([piece.column(0), pa.array([len(x) for x in raw], pa.int64()), pa.array(media, pa.binary()), pa.array(pcm, pa.binary())], names=["doc_id", "n_bytes", "media", "pcm"])

    small_batches(docs.sparkSession)
    return docs.select(docs["doc_id"].cast("long"), docs["text"]).mapInArrow(run, schema)


def measure_stored(stored: DataFrame) -> DataFrame:
    """Digests and features of stored rows (doc_id, n_bytes, media, pcm), from the stored bytes alone."""
    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"

    def run(batches):
        for piece in slices(batches, 4 << 20):
            rows, media = [], [x.as_buffer().to_pybytes() for x in piece.column(1)]
            for key, n, whole, (payload, pcm, _), wide in zip(piece.column(0).to_pylist(), piece.column(2).to_pylist(), media, from_media(media), piece.column(3), strict=True):
                rows.append((key, n, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-UNIT:]), len(whole), hashlib.sha256(whole).hexdigest(), features(pcm, np.frombuffer(wide.as_buffer(), "<i2"))))
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names=[c.split()[0] for c in schema.split(", ")])

    return stored.select("doc_id", "media", "n_bytes", "pcm").mapInArrow(run, schema)


def decode_media(media: DataFrame, rate: int = 16000) -> DataFrame:
    """Stored containers (media_id, media) of any of the three codecs as 16-bit PCM at the given rate; null media gives null."""

    def run(batches):
        for piece in slices(batches):
            there = [k for k, value in enumerate(piece.column(1)) if value.is_valid]
            out: list = [None] * piece.num_rows
            for k, (_, pcm, was) in zip(there, from_media([piece.column(1)[k].as_py() for k in there]), strict=True):
                up, down = (rate, was) if rate % was else (rate // was, 1)
                out[k] = resample(pcm, up, down).astype("<i2", copy=False).tobytes()
            yield pa.RecordBatch.from_arrays([piece.column(0), pa.array(out, pa.binary())], names=["media_id", "pcm"])

    return media.select(media["media_id"].cast("long"), media["media"]).mapInArrow(run, "media_id long, pcm binary")
