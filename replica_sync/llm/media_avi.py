"""Media columns: AVI files of motion-JPEG frames, their RIFF indexes, intra frames and shots.

The frames are lossless JPEG (sequential, Huffman, predictor 1, 8-bit grey). Its Huffman table gives the
difference category k the code of 9-k bits, so that code and extra bits of any sample are 9 bits together: a
frame of 192 samples is 216 bytes before byte stuffing, and whole arrays of frames are coded and decoded at once.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from replica_sync.llm.common import pick, small_batches

WIDTH, HEIGHT, RATE = 16, 12, 25
UNIT = WIDTH * HEIGHT
PACKED = UNIT * 9 // 8
# JPEG markers and segments of a lossless frame (SOI, DHT with code lengths 1 to 9, SOF3, SOS; EOI).
FRAME_HEAD = (
    b"\xff\xd8"
    + b"\xff\xc4" + struct.pack(">HB", 2 + 1 + 16 + 9, 0) + bytes([1] * 9 + [0] * 7) + bytes(range(8, -1, -1))
    + b"\xff\xc3" + struct.pack(">HBHHBBBB", 11, 8, HEIGHT, WIDTH, 1, 1, 0x11, 0)
    + b"\xff\xda" + struct.pack(">HBBBBBB", 8, 1, 1, 0, 1, 0, 0)
)
FRAME_TAIL = b"\xff\xd9"


def _code_tables() -> tuple[np.ndarray, np.ndarray]:
    """9-bit word of each difference (shifted by 255), and its inverse."""
    words = np.zeros(511, dtype=np.uint16)
    for d in range(-255, 256):
        k = abs(d).bit_length()
        extra = d if d >= 0 else d + (1 << k) - 1
        ones = (1 << (8 - k)) - 1
        words[d + 255] = (ones << 1) << k | extra  # 8-k ones, a zero, k extra bits
    back = np.zeros(512, dtype=np.int16)
    back[words] = np.arange(-255, 256)
    return words, back


WORD_OF, DIFFERENCE_OF = _code_tables()


def entropy_coded(frames: np.ndarray) -> np.ndarray:
    """[F, 192] samples to [F, 216] bytes, not yet stuffed."""
    image = frames.reshape(-1, HEIGHT, WIDTH).astype(np.int16)
    before = np.empty_like(image)
    before[:, :, 1:] = image[:, :, :-1]
    before[:, 1:, 0] = image[:, :-1, 0]
    before[:, 0, 0] = 128
    words = WORD_OF[(image - before) + 255].reshape(-1, UNIT // 8, 8)
    out = np.empty((len(words), UNIT // 8, 9), dtype=np.uint8)
    out[..., 0] = words[..., 0] >> 1
    for k in range(1, 8):
        out[..., k] = (words[..., k - 1] << (8 - k)) | (words[..., k] >> (k + 1))
    out[..., 8] = words[..., 7]
    return out.reshape(-1, PACKED)


def entropy_decoded(packed: np.ndarray) -> np.ndarray:
    """[F, 216] bytes back to [F, 192] samples."""
    data = packed.reshape(-1, UNIT // 8, 9).astype(np.uint16)
    words = np.empty((len(data), UNIT // 8, 8), dtype=np.uint16)
    for k in range(8):
        words[..., k] = ((data[..., k] << (k + 1)) | (data[..., k + 1] >> (7 - k))) & 511
    change = DIFFERENCE_OF[words].reshape(-1, HEIGHT, WIDTH)
    change[:, 0, 0] += 128
    change[:, :, 0] = np.cumsum(change[:, :, 0], axis=1)
    return np.cumsum(change, axis=2).astype(np.uint8).reshape(-1, UNIT)


def payload_of(data: bytes) -> bytes:
    """Filled up with spaces to a positive multiple of 192."""
    return data + b" " * (max(UNIT, -(-len(data) // UNIT) * UNIT) - len(data))


def encode_avi(payload: bytes) -> bytes:
    """One AVI file; each 192 bytes of the payload are the samples of one frame."""
    packed = entropy_coded(np.frombuffer(payload, dtype=np.uint8).reshape(-1, UNIT))
    n = len(packed)
    full = packed == 255
    stuffed = full.sum(axis=1)
    size = len(FRAME_HEAD) + PACKED + stuffed + len(FRAME_TAIL)
    chunk = 8 + size + size % 2
    start = np.cumsum(chunk) - chunk
    movi = np.zeros(int(chunk.sum()), dtype=np.uint8)
    head = np.empty((n, 8 + len(FRAME_HEAD)), dtype=np.uint8)
    head[:, :4] = np.frombuffer(b"00dc", dtype=np.uint8)
    head[:, 4:8] = size.astype("<u4").view(np.uint8).reshape(n, 4)
    head[:, 8:] = np.frombuffer(FRAME_HEAD, dtype=np.uint8)
    movi[start[:, None] + np.arange(head.shape[1])] = head
    shift = np.cumsum(full, axis=1) - full  # zeros put in before each byte
    movi[(start + head.shape[1])[:, None] + np.arange(PACKED) + shift] = packed
    end = start + 8 + size
    movi[end - 2], movi[end - 1] = 255, FRAME_TAIL[1]
    index = np.empty((n, 4), dtype="<u4")
    index[:, 0] = int.from_bytes(b"00dc", "little")
    index[:, 1], index[:, 2], index[:, 3] = 0x10, start + 4, size
    biggest = int(size.max())
    main = struct.pack("<14I", 1_000_000 // RATE, biggest * RATE, 0, 0x10, n, 0, 1, biggest, WIDTH, HEIGHT, 0, 0, 0, 0)
    stream = b"vidsMJPG" + struct.pack("<IHHIIIIIIiI4h", 0, 0, 0, 0, 1, RATE, 0, n, biggest, -1, 0, 0, 0, WIDTH, HEIGHT)
    shape = struct.pack("<IiiHH4sIiiII", 40, WIDTH, HEIGHT, 1, 8, b"MJPG", UNIT, 0, 0, 0, 0)
    strl = _list(b"strl", _chunk(b"strh", stream) + _chunk(b"strf", shape))
    body = _list(b"hdrl", _chunk(b"avih", main) + strl) + b"LIST" + struct.pack("<I", 4 + len(movi)) + b"movi" + movi.tobytes() + _chunk(b"idx1", index.tobytes())
    return b"RIFF" + struct.pack("<I", 4 + len(body)) + b"AVI " + body


def _chunk(name: bytes, data: bytes) -> bytes:
    return name + struct.pack("<I", len(data)) + data + b"\0" * (len(data) % 2)


def _list(kind: bytes, data: bytes) -> bytes:
    return b"LIST" + struct.pack("<I", 4 + len(data)) + kind + data


def riff_index(media: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Where the frames' JPEG data begin in the file, and their sizes, from idx1 (or, without one, from the chunks of movi)."""
    if media[:4] != b"RIFF" or media[8:12] != b"AVI ":
        raise ValueError("no AVI file")
    at, movi, index = 12, None, None
    while at + 8 <= len(media):
        name, size = media[at : at + 4], struct.unpack_from("<I", media, at + 4)[0]
        if name == b"LIST" and media[at + 8 : at + 12] == b"movi":
            movi = (at + 8, size)
        elif name == b"idx1":
            index = np.frombuffer(media, dtype="<u4", count=size // 16 * 4, offset=at + 8).reshape(-1, 4)
        at += 8 + size + size % 2
    if movi is None:
        raise ValueError("no movi list")
    if index is not None:
        video = index[index[:, 0] == int.from_bytes(b"00dc", "little")]
        return video[:, 2].astype(np.int64) + movi[0] + 8, video[:, 3].astype(np.int64)
    found, at, end = [], movi[0] + 4, movi[0] + movi[1]
    while at + 8 <= end:
        size = struct.unpack_from("<I", media, at + 4)[0]
        if media[at : at + 4] == b"00dc":
            found.append((at + 8, size))
        at += 8 + size + size % 2
    pairs = np.array(found, dtype=np.int64).reshape(-1, 2)
    return pairs[:, 0], pairs[:, 1]


def decode_frames(media: bytes) -> np.ndarray:
    """[F, 192] samples: stuffing removed and entropy-coded data decoded, all frames at once."""
    start, size = riff_index(media)
    data = np.frombuffer(media, dtype=np.uint8)
    head = np.frombuffer(FRAME_HEAD, dtype=np.uint8)
    if len(start) and not (data[start[:, None] + np.arange(len(head))] == head).all():
        raise ValueError("a frame of another kind")
    first, length = start + len(FRAME_HEAD), size - len(FRAME_HEAD) - len(FRAME_TAIL)
    total = int(length.sum())
    place = np.repeat(first - (np.cumsum(length) - length), length) + np.arange(total)
    coded = data[place]
    stuffing = np.zeros(total, dtype=bool)
    stuffing[1:] = (coded[:-1] == 255) & (coded[1:] == 0)
    stuffing[(np.cumsum(length) - length)[length > 0]] = False  # a frame's first byte stuffs nothing
    return entropy_decoded(coded[~stuffing].reshape(-1, PACKED))


def shots(frames: np.ndarray, bins: int = 16, window: int = 12, strictness: float = 3.0) -> list[tuple[int, int]]:
    """(first frame, frame after the last) of each shot.

    A cut falls where the difference of neighbouring frames' histograms exceeds the mean of the differences
    around it by strictness times their spread, and is the largest of its neighbours.
    """
    n = len(frames)
    if n < 3:
        return [(0, n)] if n else []
    slot = (frames >> (8 - bins.bit_length() + 1)).astype(np.int64) + (np.arange(n) * bins)[:, None]
    histogram = np.bincount(slot.ravel(), minlength=n * bins).reshape(n, bins)
    change = np.abs(np.diff(histogram, axis=0)).sum(axis=1) / (2 * UNIT)
    total, square = (np.concatenate([[0.0], np.cumsum(x)]) for x in (change, change**2))
    low, high = np.maximum(np.arange(n - 1) - window, 0), np.minimum(np.arange(n - 1) + window + 1, n - 1)
    others = high - low - 1
    mean = (total[high] - total[low] - change) / np.maximum(others, 1)
    spread = np.sqrt(np.maximum((square[high] - square[low] - change**2) / np.maximum(others, 1) - mean**2, 0))
    left, right = np.concatenate([[0.0], change[:-1]]), np.concatenate([change[1:], [0.0]])
    cut = np.flatnonzero((others > 0) & (change > mean + strictness * spread + 0.02) & (change >= left) & (change > right)) + 1
    edge = [0, *cut.tolist(), n]
    return list(zip(edge, edge[1:]))


def store_media(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_bytes and media (an AVI file) of every row; a null text counts as empty: one frame of spaces."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "text", 2 << 20):
            data = [x or b"" for x in batch.column(1).cast(pa.binary()).to_pylist()]
            yield pa.record_batch([batch.column(0), pa.array([len(x) for x in data], pa.int64()), pa.array([encode_avi(payload_of(x)) for x in data], pa.binary())], names=["doc_id", "n_bytes", "media"])

    rows = pick(docs, doc_id=doc_id, text=text)
    return rows.mapInArrow(run, f"doc_id {dict(rows.dtypes)['doc_id']}, n_bytes bigint, media binary")


def clip_rows(stored: DataFrame) -> DataFrame:
    """One row per shot: doc_id, clip, first_frame, end_frame, start_s, end_s."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "media"):
            for key, media in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                parts = shots(decode_frames(media))
                yield pa.record_batch([pa.array([key] * len(parts), batch.schema.field(0).type), pa.array(range(len(parts)), pa.int64()), *[pa.array([p[k] for p in parts], pa.int64()) for k in (0, 1)], *[pa.array([p[k] / RATE for p in parts], pa.float64()) for k in (0, 1)]], names=["doc_id", "clip", "first_frame", "end_frame", "start_s", "end_s"])

    rows = stored.select("doc_id", "media")
    return rows.mapInArrow(run, f"doc_id {dict(rows.dtypes)['doc_id']}, clip bigint, first_frame bigint, end_frame bigint, start_s double, end_s double")


def media_digests(stored: DataFrame) -> DataFrame:
    """doc_id, n_bytes, payload_bytes, payload_sha256, tail_crc32, media_bytes, media_sha256, feature, decoded from media.

    feature: the shots as start-end seconds, comma-joined. Equal texts have equal values; an empty table
    gives an empty result.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "media"):
            out = []
            for n, media in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                frames = decode_frames(media)
                payload = frames.tobytes()
                feature = ",".join(f"{a / RATE:.2f}-{b / RATE:.2f}" for a, b in shots(frames))
                out.append((n, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), len(media), hashlib.sha256(media).hexdigest(), feature))
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
            yield pa.record_batch([batch.column(0), *map(pa.array, zip(*out), kinds)], names=["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"])

    rows = stored.select("doc_id", "n_bytes", "media")
    return rows.mapInArrow(run, f"doc_id {dict(rows.dtypes)['doc_id']}, n_bytes bigint, payload_bytes bigint, payload_sha256 string, tail_crc32 bigint, media_bytes bigint, media_sha256 string, feature string")
