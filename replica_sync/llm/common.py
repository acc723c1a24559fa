"""What several operators share: folders that all executors see, batches of bounded size, word hashes."""

from __future__ import annotations

import ctypes
import functools
import re
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Fixed value: the words of a text are the runs of bytes outside these.
WORD = "[^\\x20\\x09-\\x0D]+"


def shared_folder(spark: SparkSession, name: str) -> str:
    """A new folder below spark.checkpoint.dir, or the context's checkpoint folder; a temporary one only in local mode, where all share one machine."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        kept = spark.sparkContext._jsc.sc().getCheckpointDir()
        base = kept.get() if kept.isDefined() else None
    if not base and spark.sparkContext.master.startswith("local["):
        base = "file://" + tempfile.mkdtemp(prefix="replica_sync_")
        spark.sparkContext.setCheckpointDir(base)
    if not base:
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


#: Runtime setting by which Spark deletes a query's exchange files as soon as the query has ended.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def kept_as_table(df: DataFrame, name: str) -> DataFrame:
    """Writes df to the shared folder and reads it again: the lineage ends there and lost executors cost nothing.

    Once the table is written, the exchange files that led to it go: nothing reads them again.
    """
    spark = df.sparkSession
    path = shared_folder(spark, name)
    before = spark.conf.get(CLEANUP, "false")
    spark.conf.set(CLEANUP, "true")
    try:
        df.write.parquet(path)
    finally:
        spark.conf.set(CLEANUP, before)
    table = spark.read.schema(df.schema).parquet(path)
    table.kept_at = path
    return table


def dropped(*tables: DataFrame) -> None:
    """Deletes kept tables that nothing will read again."""
    for table in tables:
        spark = table.sparkSession
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(table.kept_at)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


@functools.cache
def _allocator() -> ctypes.CDLL | None:
    try:
        return ctypes.CDLL("libc.so.6")
    except OSError:
        return None


def trim() -> None:
    """Gives memory that a block's arrays took back to the system, so that idle workers hold none of it."""
    pa.default_memory_pool().release_unused()
    if _allocator() is not None:
        _allocator().malloc_trim(0)


def pick(df: DataFrame, **columns: str) -> DataFrame:
    """Only the named columns, under the operator's own names: extra or clashing columns go."""
    return df.select(*[F.col(f"`{old}`").alias(new) for new, old in columns.items()])


def by_place(df: DataFrame) -> DataFrame:
    """Columns named c0, c1, ...: mapInArrow takes names with dots for nested fields."""
    return df.toDF(*[f"c{i}" for i in range(len(df.columns))])


def small_batches(batches: Iterator[pa.RecordBatch], column: str, most_bytes: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """Cuts batches so that each holds about most_bytes of the column; one longer row makes a batch of its own."""
    for batch in batches:
        if not batch.num_rows:
            continue
        values = batch.column(batch.schema.get_field_index(column))
        size = np.asarray(pc.fill_null(pc.binary_length(values), 0), dtype=np.int64)
        share = np.cumsum(size) // most_bytes
        cuts = [0, *(np.flatnonzero(np.diff(share)) + 1).tolist(), batch.num_rows]
        for a, b in zip(cuts, cuts[1:]):
            yield batch.slice(a, b - a)


def splitter(pattern: str) -> Callable[[str], list[str]]:
    """All matches of a pattern with \\p{L} and \\p{N}. ASCII texts take the standard library's engine, with the classes' ASCII
    members spelt out; the matches are the same.
    """
    import regex

    whole = regex.compile(pattern).findall
    plain = pattern.replace("[^\\s\\p{L}\\p{N}]", "[^\\sA-Za-z0-9]").replace("\\p{L}", "[A-Za-z]").replace("\\p{N}", "[0-9]")
    if "\\p" in plain:
        return whole
    ascii_only = re.compile(plain, re.A).findall
    return lambda text: ascii_only(text) if text.isascii() else whole(text)


_WHITE = np.zeros(256, dtype=bool)
_WHITE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def _powers(base: int, n: int) -> np.ndarray:
    """base ** (0 ... n-1) modulo 2**64, by doubling."""
    out = np.ones(1, dtype=np.uint64)
    factor = np.uint64(base)
    while len(out) < n:
        out = np.concatenate([out, out * factor])
        factor = np.uint64(int(factor) ** 2 % 2**64)
    return out[:n]


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words that spreads every input bit (two rounds of xor-shift and multiply)."""
    x = x ^ (x >> np.uint64(32))
    x = x * np.uint64(0xD6E8FEB86659FD93)
    x = x ^ (x >> np.uint64(32))
    x = x * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


_SHAPE = np.arange(256, dtype=np.uint8)
_SHAPE[65:91], _SHAPE[97:123], _SHAPE[128:], _SHAPE[48:58] = 65, 97, 97, 57


class Words:
    """The words of many texts at once: .hash of each word (64 bits, A-Z lowered), .doc it belongs to, .start and .end bytes.

    With shapes, letters become A or a, digits 9, and runs of one sign a single one, before words are hashed.
    """

    BASE = 0x9E3779B97F4A7C15
    INVERSE = pow(BASE, -1, 2**64)
    PIECE = 1 << 17
    _up = _down = np.ones(1, dtype=np.uint64)

    def __init__(self, texts: list[bytes], lower: bool = True, shapes: bool = False):
        data = np.frombuffer(b"\n".join(texts) + b"\n", dtype=np.uint8)
        bounds = np.cumsum([len(t) + 1 for t in texts]) if texts else np.zeros(0, dtype=np.int64)
        if shapes and texts:
            data = _SHAPE[data]
            keep = np.ones(len(data), dtype=bool)
            keep[1:] = (data[1:] != data[:-1]) | _WHITE[data[1:]]
            bounds, data = np.cumsum(keep)[bounds - 1], data[keep]
        space = _WHITE[data]
        edge = np.diff(np.concatenate([[True], space, [True]]).astype(np.int8))
        self.start, self.end = np.flatnonzero(edge == -1), np.flatnonzero(edge == 1)
        self.doc = np.searchsorted(bounds, self.start, side="right")
        self.bytes = _LOWER[data] if lower and not shapes else data
        self.hash = np.empty(len(self.start), dtype=np.uint64)
        a = 0
        while a < len(self.start):  # in pieces that stay in the processor's cache; a longer word is a piece of its own
            b = max(a + 1, int(np.searchsorted(self.end, self.start[a] + self.PIECE, side="right")))
            self.hash[a:b] = self._hashes(int(self.start[a]), self.start[a:b], self.end[a:b])
            a = b
        self.count = np.bincount(self.doc, minlength=len(texts)).astype(np.int64)
        self.first = np.concatenate([[0], np.cumsum(self.count)])[:-1].astype(np.int64)

    def _hashes(self, base: int, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        data = self.bytes[base : int(end[-1])]
        n = len(data)
        if n >= len(Words._up):
            Words._up, Words._down = _powers(self.BASE, n + 1), _powers(self.INVERSE, n + 1)
        run = np.zeros(n + 1, dtype=np.uint64)
        np.cumsum((data.astype(np.uint64) + np.uint64(1)) * Words._up[:n], out=run[1:])
        return mixed((run[end - base] - run[start - base]) * Words._down[start - base] + (end - start).astype(np.uint64) * np.uint64(0xA24BAED4963EE407))


def texts_of(batch: pa.RecordBatch, column: str = "text") -> list[bytes]:
    """UTF-8 of the column's texts; null counts as empty."""
    return [x or b"" for x in batch.column(batch.schema.get_field_index(column)).cast(pa.binary()).to_pylist()]
