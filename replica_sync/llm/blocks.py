"""Corpus counts for blocks of rows, by two exchanges of packed messages.

Rows are dealt to blocks of bounded size. Each block sends a key range its own sorted keys in that range with their
counts, and nothing where it has none. A range adds the counts up and answers with one bit for each key of the message,
whether another block has it too, and the totals of those that do; for all others the block's own
count is the total. So each block learns exact corpus counts of its own keys, nothing is broadcast, no range
gets a key more than once from a block however frequent it is, and messages are never more than keys.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Bytes of input, as the optimizer estimates them, that make a block.
BLOCK_BYTES = 2 << 20
REQUEST = "part int, block bigint, words binary, grams binary"
REPLY = "block bigint, part int, words binary, grams binary"


def plan_bytes(rows: DataFrame) -> int:
    """The plan's size; where that is unknown, from the number of input partitions."""
    size = int(str(rows._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return size if size < 1 << 55 else 2 * BLOCK_BYTES * rows.rdd.getNumPartitions()


def block_count(rows: DataFrame, each: int = BLOCK_BYTES) -> int:
    return max(1, -(-plan_bytes(rows) // each))


def key_bits(rows: DataFrame, spare: int = 20) -> int:
    """Bits of a hash with which a key of so much text meets another one by a chance of about 2**-spare at most."""
    return min(64, max(44, math.ceil(math.log2(plan_bytes(rows) + 1)) + spare))


def block_of(rows: DataFrame, n: int) -> Column:
    """A hash of the whole row: copies under different ids spread over all blocks."""
    return F.pmod(F.xxhash64(*rows.columns), F.lit(n))


def in_blocks(rows: DataFrame, n: int) -> DataFrame:
    return rows.withColumn("block", block_of(rows, n)).repartition(n, "block")


def range_count(rows: DataFrame, blocks: int) -> int:
    return max(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), blocks)


def packed_counts(counts: np.ndarray) -> bytes:
    """Counts as bytes, those of 255 and more apart."""
    large = np.flatnonzero(counts >= 255)
    return np.array([len(large)], dtype="<u8").tobytes() + large.astype("<u8").tobytes() + counts[large].astype("<u8").tobytes() + np.minimum(counts, 255).astype(np.uint8).tobytes()


def unpacked_counts(data: bytes, n: int, at: int = 0) -> np.ndarray:
    large = int(np.frombuffer(data, dtype="<u8", count=1, offset=at)[0])
    at += 8
    counts = np.frombuffer(data, dtype=np.uint8, count=n, offset=at + 16 * large).astype(np.int64)
    counts[np.frombuffer(data, dtype="<u8", count=large, offset=at).astype(np.int64)] = np.frombuffer(data, dtype="<u8", count=large, offset=at + 8 * large)
    return counts


def packed(keys: np.ndarray, counts: np.ndarray) -> bytes:
    """Sorted distinct 64-bit keys as gaps of as many bytes as the widest one takes but for a few, and their counts: exact."""
    gaps = np.diff(keys, prepend=np.uint64(0))
    gaps[:1] = 0
    width = 8
    if len(keys) > 1:
        most = np.partition(gaps, -1 - len(gaps) // 256)[-1 - len(gaps) // 256]  # all but one in 256 fit
        width = max(1, -(-int(most).bit_length() // 8))
    wide = np.flatnonzero(gaps >> np.uint64(8 * width - 1) >> np.uint64(1))
    body = gaps.view(np.uint8).reshape(-1, 8)[:, :width].tobytes()
    head = np.array([len(keys), width, len(wide), keys[0] if len(keys) else 0], dtype="<u8").tobytes()
    return head + wide.astype("<u8").tobytes() + gaps[wide].astype("<u8").tobytes() + body + packed_counts(counts)


def unpacked(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    n, width, wide = np.frombuffer(data, dtype="<u8", count=3).astype(int).tolist()
    first = np.frombuffer(data, dtype="<u8", count=1, offset=24)[0]
    at = 32 + 16 * wide
    gaps = np.zeros((n, 8), dtype=np.uint8)
    gaps[:, :width] = np.frombuffer(data, dtype=np.uint8, count=n * width, offset=at).reshape(n, width)
    gaps = gaps.view("<u8").ravel()
    gaps[np.frombuffer(data, dtype="<u8", count=wide, offset=32).astype(np.int64)] = np.frombuffer(data, dtype="<u8", count=wide, offset=32 + 8 * wide)
    gaps[:1] = first
    return np.cumsum(gaps, dtype=np.uint64), unpacked_counts(data, n, at + n * width)


def counted(keys: np.ndarray, weight: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sorted distinct keys, the sum of weights of each, and each entry's place among them."""
    order = np.argsort(keys)
    found = keys[order]
    first = np.ones(len(found), dtype=bool)
    first[1:] = found[1:] != found[:-1]
    found, place = found[first], np.empty(len(keys), dtype=np.int32)
    place[order] = np.cumsum(first, dtype=np.int32) - np.int32(1)
    del order, first
    return found, np.bincount(place, weight, minlength=len(found)).astype(np.int64), place


def cuts_of(keys: np.ndarray, parts: int, bits: int = 64) -> np.ndarray:
    """Where each key range begins among sorted keys of so many bits."""
    of = ((keys >> np.uint64(bits - 32)) * np.uint64(parts)) >> np.uint64(32)
    return np.searchsorted(of, np.arange(parts + 1))


Counted = tuple[np.ndarray, np.ndarray]
NONE: Counted = (np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.int64))


def requests(block: int, words: Counted, grams: Counted, parts: int, bits: int = 64) -> Iterator[tuple]:
    """Rows of REQUEST, one for each key range in which the block has keys. Words have 64 bits, grams so many."""
    cut = [cuts_of(words[0], parts), cuts_of(grams[0], parts, bits)]
    for p in np.flatnonzero(np.diff(cut[0]) + np.diff(cut[1])).tolist():
        yield p, block, *(packed(*(y[c[p] : c[p + 1]] for y in x)) for c, x in zip(cut, (words, grams)))


def request_table(rows: list[tuple]) -> pa.Table:
    kinds = [pa.int32(), pa.int64(), pa.binary(), pa.binary()]
    columns = list(zip(*rows)) if rows else [[]] * 4
    return pa.table([pa.array(c, k) for c, k in zip(columns, kinds)], names=["part", "block", "words", "grams"])


def _answers(messages: list[bytes]) -> list[bytes]:
    """For each message a bit for each of its keys, whether another message has it, and the totals of those."""
    split = [unpacked(m) for m in messages]
    found, place, times = np.unique(np.concatenate([k for k, _ in split]), return_inverse=True, return_counts=True)
    totals = np.bincount(place, np.concatenate([c for _, c in split]), minlength=len(found)).astype(np.int64)
    shared, total, out, at = (times > 1)[place], totals[place], [], 0
    for k, _ in split:
        mine = slice(at, at + len(k))
        at += len(k)
        out.append(np.packbits(shared[mine]).tobytes() + packed_counts(total[mine][shared[mine]]))
    return out


def replies(asked: DataFrame) -> DataFrame:
    """REQUEST rows to REPLY rows."""

    def answer(table: pa.Table) -> pa.Table:
        from replica_sync.llm.common import trim

        out = pa.table([table.column("block"), table.column("part"), *(pa.array(_answers(table.column(c).to_pylist()), pa.binary()) for c in ("words", "grams"))], names=[x.split()[0] for x in REPLY.split(", ")])
        trim()
        return out

    return asked.groupBy("part").applyInArrow(answer, REPLY)


def corrected(keys: np.ndarray, counts: np.ndarray, answers: list[tuple[int, bytes]], parts: int, bits: int = 64) -> np.ndarray:
    """The block's own counts with the totals of the answers (key range, message) put in."""
    counts, cut = counts.copy(), cuts_of(keys, parts, bits)
    for p, message in answers:
        n = int(cut[p + 1] - cut[p])
        size = -(-n // 8)
        shared = np.flatnonzero(np.unpackbits(np.frombuffer(message, dtype=np.uint8, count=size), count=n))
        counts[cut[p] + shared] = unpacked_counts(message, len(shared), size)
    return counts
