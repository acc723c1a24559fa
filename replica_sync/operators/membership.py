"""Membership filters of sets of parts: sizing, building, probing. One filter per session, whatever the segments.

A filter is stored in blocks: sid, n_parts, m_bits, k, block and the block's bits. No task holds more than a block, no filter is
broadcast: parts ask each block for bits, two bytes a bit, and one bit each comes back. Segments only say which parts ask together.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType, StructField, StructType

LN2 = math.log(2)
#: Bits of a block: an offset takes two bytes.
BLOCK_BITS = 1 << 16
#: Parts whose bits a task packs at a time.
PACKED_PARTS = 1 << 16
ASKED = "sid bigint, block bigint, seg int, offsets binary"


def filter_shape(n: int, eps: float) -> tuple[int, int]:
    """Bits and hashes for n parts and a share eps of false positives."""
    m = max(1, math.ceil(-n * math.log(eps) / LN2**2))
    return m, max(1, round(-math.log(eps) / LN2))


def filter_shape_bits(n: int, bits_per_part: int, k: int) -> tuple[int, int]:
    return max(1, n * bits_per_part), k


def hashes_for(eps: Column) -> Column:
    return F.greatest(F.round(-F.ln(eps) / F.lit(LN2)), F.lit(1)).cast("int")


def bits_for(n: Column, eps: Column) -> Column:
    return F.greatest(F.ceil(-n * F.ln(eps) / F.lit(LN2**2)), F.lit(1)).cast("bigint")


def shaped(parts: DataFrame, settings: DataFrame, bits_per_part: int | None = None, k: int | None = None) -> DataFrame:
    """sid, n_parts, m_bits, k of the filters to build; settings has sid, eps."""
    sizes = parts.groupBy("sid").agg(F.count("*").alias("n_parts")).join(settings.select("sid", "eps"), "sid")
    if bits_per_part:
        return sizes.select("sid", "n_parts", F.greatest(F.col("n_parts") * bits_per_part, F.lit(1)).cast("bigint").alias("m_bits"), F.lit(k).alias("k"))
    return sizes.select("sid", "n_parts", bits_for(F.col("n_parts"), F.col("eps")).alias("m_bits"), hashes_for(F.col("eps")).alias("k"))


def position(i: Column | int) -> Column:
    """The i-th bit of a part in a filter: double hashing with two 60-bit halves of the digest, reduced before multiplying."""
    step = i if isinstance(i, Column) else F.lit(i)
    return (F.col("d") % F.col("m_bits") + step * (F.col("d2") % F.col("m_bits"))) % F.col("m_bits")


def filter_words(parts: DataFrame, shapes: DataFrame) -> DataFrame:
    """sid, word, bits: the non-zero words of 32 bits. Partial aggregates: at most a filter's words per task are exchanged."""
    located = parts.select("sid", "d", "d2").join(F.broadcast(shapes.select("sid", "m_bits", "k")), "sid")  # one row a session
    bits = located.select("sid", "m_bits", "d", "d2", F.explode(F.sequence(F.lit(0), F.col("k") - 1)).alias("i")).select("sid", position(F.col("i").cast("bigint")).alias("p"))
    return bits.groupBy("sid", F.floor(F.col("p") / 32).cast("int").alias("word")).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("bigint"), (F.col("p") % 32).cast("int"))).alias("bits"))


def positions(d: np.ndarray, d2: np.ndarray, m: int, k: int) -> np.ndarray:
    """As position, of all parts: k in a row for each."""
    return ((d % m)[:, None] + np.arange(k, dtype=np.int64) * (d2 % m)[:, None]).ravel() % m


def by_block(at: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    """(block, offsets) of ascending blocks; positions of a block keep their order."""
    block = at // BLOCK_BITS
    order = np.argsort(block, kind="stable")
    block, offsets = block[order], (at[order] % BLOCK_BITS).astype("<u2")
    for piece in np.split(np.arange(len(at)), np.flatnonzero(np.diff(block)) + 1) if len(at) else ():
        yield int(block[piece[0]]), offsets[piece[0] : piece[-1] + 1]


def asked_table(rows: list[tuple[int, int, int, bytes]]) -> pa.Table:
    kinds = (pa.int64(), pa.int64(), pa.int32(), pa.binary())
    return pa.table([pa.array([r[j] for r in rows], kind) for j, kind in enumerate(kinds)], names=[c.split()[0] for c in ASKED.split(", ")])


def filter_blocks(parts: DataFrame, shapes: DataFrame) -> DataFrame:
    """sid, block, bits of the blocks with set bits. Tasks pack their parts' bits by block before the exchange."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []

        def packed() -> Iterator[pa.RecordBatch]:
            sid, d, d2, m, k = (np.concatenate([b.column(j).to_numpy(zero_copy_only=False) for b in held]) for j in range(5))
            held.clear()
            rows = []
            for s in np.unique(sid):
                own = np.flatnonzero(sid == s)
                at = np.unique(positions(d[own], d2[own], int(m[own[0]]), int(k[own[0]])))
                rows += [(int(s), block, 0, offsets.tobytes()) for block, offsets in by_block(at)]
            yield from asked_table(rows).to_batches()

        for batch in batches:
            if batch.num_rows:
                held.append(batch)
            if sum(b.num_rows for b in held) >= PACKED_PARTS:
                yield from packed()
        if held:
            yield from packed()

    def fill(key: tuple, table: pa.Table) -> pa.Table:
        bits = np.zeros(BLOCK_BITS, dtype=bool)
        for offsets in table.column("offsets"):
            bits[np.frombuffer(offsets.as_py(), dtype="<u2")] = True
        return pa.table([pa.array([key[0].as_py()], pa.int64()), pa.array([key[1].as_py()], pa.int64()), pa.array([np.packbits(bits).tobytes()], pa.binary())], names=["sid", "block", "bits"])

    shape = F.broadcast(shapes.select("sid", "m_bits", "k"))  # one row a session
    located = parts.select("sid", "d", "d2").join(shape, "sid").select("sid", "d", "d2", "m_bits", "k")
    return located.mapInArrow(pack, ASKED).groupBy("sid", "block").applyInArrow(fill, "sid bigint, block bigint, bits binary")


def build_filter(parts: DataFrame, settings: DataFrame, bits_per_part: int | None = None, k: int | None = None) -> DataFrame:
    """sid, n_parts, m_bits, k, block, bits of the filters over parts: a row a block."""
    shapes = shaped(parts, settings, bits_per_part, k)
    return filter_blocks(parts, shapes).join(F.broadcast(shapes), "sid").select("sid", "n_parts", "m_bits", "k", "block", "bits")  # one row a session


def shapes_of(filters: DataFrame) -> DataFrame:
    return filters.groupBy("sid").agg(F.max("m_bits").alias("m_bits"), F.max("k").alias("k"))


def probed(parts: DataFrame, filters: DataFrame) -> DataFrame:
    """Adds hit: whether all bits of the part are set. A session without a filter has an empty one: no hits.

    The parts of a session and segment ask together: a row for each block with the offsets wanted of it, answered by a row of bits
    in the same order.
    """
    shape = F.broadcast(shapes_of(filters))  # one row a session
    known, columns = parts.join(shape, "sid", "left"), parts.columns

    def order_of(table: pa.Table) -> tuple[np.ndarray, np.ndarray, int]:
        """Positions of the distinct digests in ascending order, where each row's digest stands there, and k."""
        d, d2 = (table.column(c).to_numpy() for c in ("d", "d2"))
        order = np.lexsort((d2, d))
        d, d2 = d[order], d2[order]
        new = np.concatenate([[True], (np.diff(d) != 0) | (np.diff(d2) != 0)])
        back = np.empty(len(d), dtype=np.int64)
        back[order] = np.cumsum(new) - 1
        m, k = table.column("m_bits")[0].as_py(), table.column("k")[0].as_py()
        return positions(d[new], d2[new], m, k), back, k

    def ask(key: tuple, table: pa.Table) -> pa.Table:
        at, _, _ = order_of(table)
        return asked_table([(key[0].as_py(), block, key[1].as_py(), offsets.tobytes()) for block, offsets in by_block(at)])

    def answer(key: tuple, wanted: pa.Table, stored: pa.Table) -> pa.Table:
        bits = np.unpackbits(np.frombuffer(stored.column("bits")[0].as_py(), dtype=np.uint8)) if stored.num_rows else np.zeros(BLOCK_BITS, dtype=np.uint8)
        found = [np.packbits(bits[np.frombuffer(o.as_py(), dtype="<u2")]).tobytes() for o in wanted.column("offsets")]
        return pa.table([wanted.column("sid"), wanted.column("seg"), wanted.column("block"), pa.array(found, pa.binary())], names=["sid", "seg", "block", "found"])

    def judge(key: tuple, table: pa.Table, answers: pa.Table) -> pa.Table:
        own = table.select(columns)
        if not table.num_rows or table.column("m_bits")[0].as_py() is None:
            return own.append_column("hit", pa.array(np.zeros(table.num_rows, dtype=bool)))
        at, back, k = order_of(table)
        told = dict(zip(answers.column("block").to_pylist(), answers.column("found").to_pylist()))
        flat = [np.unpackbits(np.frombuffer(told[block], dtype=np.uint8), count=len(offsets)) for block, offsets in by_block(at)]
        set_ = np.empty(len(at), dtype=bool)
        set_[np.argsort(at // BLOCK_BITS, kind="stable")] = np.concatenate(flat)
        return own.append_column("hit", pa.array(set_.reshape(-1, k).all(axis=1)[back]))

    wanted = known.where("m_bits is not null").select("sid", "seg", "d", "d2", "m_bits", "k").groupBy("sid", "seg").applyInArrow(ask, ASKED)
    stored = filters.select("sid", "block", "bits")
    answers = wanted.groupBy("sid", "block").cogroup(stored.groupBy("sid", "block")).applyInArrow(answer, "sid bigint, seg int, block bigint, found binary")
    schema = StructType([*parts.schema.fields, StructField("hit", BooleanType())])
    return known.groupBy("sid", "seg").cogroup(answers.groupBy("sid", "seg")).applyInArrow(judge, schema)


def split_by_filter(parts: DataFrame, filters: DataFrame, most_hashes: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(perhaps common, certainly exclusive) parts. A session without a filter has an empty one: all exclusive. Filters know their hashes; most_hashes is not needed."""
    tested = probed(parts, filters)
    return tested.where("hit").drop("hit"), tested.where("not hit").drop("hit")


def filter_bytes(filters: DataFrame) -> DataFrame:
    """sid, metadata_bytes: bits rounded up to bytes."""
    return shapes_of(filters).select("sid", F.ceil(F.col("m_bits") / 8).cast("bigint").alias("metadata_bytes"))


def measured_fpr(filters: DataFrame, probe: DataFrame, truth: DataFrame) -> DataFrame:
    """One row per session: tested, hits, rate over the probes that are not members."""
    strangers = probe.join(truth.select("sid", "h"), ["sid", "h"], "left_anti")
    tested = probed(strangers, filters)
    return tested.groupBy("sid").agg(F.count("*").alias("tested"), F.count_if("hit").alias("hits"), (F.count_if("hit") / F.count("*")).alias("rate"))
