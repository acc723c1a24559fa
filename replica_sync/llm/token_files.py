"""Token ids in Arrow IPC files: record batches of equal-length sequences as fixed-size lists.

Each file holds rows (ids: fixed_size_list<uint16 or uint32>[L], mask: fixed_size_list<bool>[L]); the last
row of a file is filled up with zeros under a false mask. Read through a memory map, the ids of all rows
are one contiguous buffer: sequence k is the slice [k*L, (k+1)*L), without copying.
"""

from __future__ import annotations

import os
import re
import uuid
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from replica_sync.llm.common import kept_as_table, pick, shared_folder, small_batches, splitter

#: Pieces a worker remembers; beyond it the memory starts anew, results stay the same.
REMEMBERED = 1_500_000
TOGETHER = 100


class LibraryTokenizer:
    """The tokenizers library, asked once per distinct piece of its own pre-tokenizer's pattern."""

    def __init__(self, path: str, pattern: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        added = sorted((x.content for x in self.library.get_added_tokens_decoder().values()), key=len, reverse=True)
        #: Texts with one of the library's own added tokens are given to it whole.
        self.added = re.compile("|".join(map(re.escape, added))) if added else None
        self.dtype = np.dtype("<u2") if self.library.get_vocab_size() <= 1 << 16 else np.dtype("<u4")
        self.split = splitter(pattern)
        self.known: dict[str, bytes] = {}

        self.line_feed = self.library.encode("\n", add_special_tokens=False).ids

    def encode_many(self, texts: list[str]) -> list[bytes]:
        whole = {i for i, x in enumerate(texts) if self.added and self.added.search(x)}
        split = [[] if i in whole else self.split(x) for i, x in enumerate(texts)]
        new = set().union(*split).difference(self.known)
        if len(self.known) + len(new) > REMEMBERED:
            self.known.clear()
            new = set().union(*split)
        self._learn(list(new))
        ids = self.known.__getitem__
        out = [b"".join(map(ids, pieces)) for pieces in split]
        for i in whole:
            out[i] = np.array(self.library.encode(texts[i], add_special_tokens=False).ids, dtype=self.dtype).tobytes()
        return out

    def _learn(self, pieces: list[str]) -> None:
        """Asks the library. Words go many to a text, parted by line feeds: those are pieces of their own, which no word contains."""
        words = [x for x in pieces if x.removeprefix(" ").isalpha()] if len(self.line_feed) == 1 else []
        groups = [words[i : i + TOGETHER] for i in range(0, len(words), TOGETHER)]
        for group, found in zip(groups, self.library.encode_batch(["\n".join(g) for g in groups], add_special_tokens=False)):
            ids = np.array(found.ids, dtype=self.dtype)
            cut = np.flatnonzero(ids == self.line_feed[0]).tolist()
            data, size = ids.tobytes(), self.dtype.itemsize
            for word, a, b in zip(group, [0, *(x + 1 for x in cut)], [*cut, len(ids)]):
                self.known[word] = data[a * size : b * size]
        rest = list(set(pieces).difference(words))
        for piece, found in zip(rest, self.library.encode_batch(rest, add_special_tokens=False)):
            self.known[piece] = np.array(found.ids, dtype=self.dtype).tobytes()


@lru_cache(maxsize=2)
def library_tokenizer(path: str, pattern: str) -> LibraryTokenizer:
    return LibraryTokenizer(path, pattern)


def _store(folder: str):
    """The file system of a folder's URI and the path in it."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(folder if "://" in folder or folder.startswith("file:") else "file://" + folder)


class SequenceWriter:
    """Gathers ids and writes full record batches; memory is one batch."""

    def __init__(self, folder: str, name: str, dtype: np.dtype, length: int, rows: int):
        self.store, base = _store(folder)
        self.store.create_dir(base, recursive=True)
        self.path, self.length, self.rows, self.dtype = f"{base}/{name}", length, rows, dtype
        self.sink = self.store.open_output_stream(self.path)
        ids, mask = pa.list_(pa.from_numpy_dtype(dtype), length), pa.list_(pa.bool_(), length)
        self.file = pa.ipc.new_file(self.sink, pa.schema([("ids", ids), ("mask", mask)]))
        self.parts: list[bytes] = []
        self.held, self.total = 0, 0

    def add(self, ids: bytes) -> int:
        """Appends one document's ids; where they start in this file."""
        at = self.total
        n = len(ids) // self.dtype.itemsize
        self.parts.append(ids)
        self.held += n
        self.total += n
        if self.held >= self.length * self.rows:
            self._write(False)
        return at

    def _write(self, last: bool) -> None:
        data = np.frombuffer(b"".join(self.parts), dtype=self.dtype)
        full = self.length * self.rows
        whole = len(data) // full * full
        for a in range(0, whole, full):
            self._batch(data[a : a + full], full)
        rest = data[whole:]
        if last and len(rest):
            n = -(-len(rest) // self.length) * self.length
            self._batch(np.concatenate([rest, np.zeros(n - len(rest), dtype=self.dtype)]), len(rest))
            rest = rest[:0]
        self.parts, self.held = [rest.tobytes()], len(rest)

    def _batch(self, data: np.ndarray, valid: int) -> None:
        ids = pa.FixedSizeListArray.from_arrays(pa.array(data), self.length)
        mask = pa.FixedSizeListArray.from_arrays(pa.array(np.arange(len(data)) < valid), self.length)
        self.file.write_batch(pa.record_batch([ids, mask], names=["ids", "mask"]))

    def close(self) -> None:
        self._write(True)
        self.file.close()
        self.sink.close()


class SequenceReader:
    """Random access to one file: sequences, masks and runs of ids, zero-copy on a local or shared mount."""

    def __init__(self, folder: str, name: str):
        store, base = _store(folder)
        path = f"{base}/{name}"
        self.source = pa.memory_map(path) if store.type_name == "local" else store.open_input_file(path)
        self.file = pa.ipc.open_file(self.source)
        self.length = self.file.schema.field("ids").type.list_size
        self.rows = self.file.get_batch(0).num_rows if self.file.num_record_batches else 1

    def _flat(self, batch: int, column: str) -> pa.Array:
        return self.file.get_batch(batch).column(column).flatten()

    def sequence(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids and mask of the k-th sequence."""
        batch, row = divmod(k, self.rows)
        part = slice(row * self.length, (row + 1) * self.length)
        return self._flat(batch, "ids").to_numpy(zero_copy_only=True)[part], self._flat(batch, "mask").to_numpy(zero_copy_only=False)[part]

    def run(self, start: int, n: int) -> np.ndarray:
        """n ids from a position on."""
        each, out = self.rows * self.length, []
        while n:
            batch, at = divmod(start, each)
            part = self._flat(batch, "ids").to_numpy(zero_copy_only=True)[at : at + n]
            out.append(part)
            start, n = start + len(part), n - len(part)
        return out[0] if len(out) == 1 else np.concatenate(out) if out else np.zeros(0, dtype="<u2")


@lru_cache(maxsize=4)
def sequence_reader(folder: str, name: str) -> SequenceReader:
    return SequenceReader(folder, name)


def write_token_files(docs: DataFrame, folder: str, doc_id: str = "doc_id", text: str = "text", path: str | None = None, pattern: str | None = None, end_id: int = 0, length: int = 2048, rows: int = 64) -> DataFrame:
    """Writes the ids of all texts, each followed by end_id, in ascending doc_id order; the index rows come back.

    Index: doc_id, file, part, offset (in the file), n_tokens, start (in the whole stream). One file per
    partition of a range exchange, named by partition and attempt, so that a repeated task cannot spoil
    what the index names. A null text counts as empty: it holds the end id alone. Null ids come first, rows of equal id in the
    order of their texts; an empty table gives no files and an empty index.
    """
    import public_tokenizers

    path, pattern = path or public_tokenizers.path("byte_bpe_50k.json"), pattern or public_tokenizers.PATTERN

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, writer = TaskContext.get().partitionId(), None
        for batch in small_batches(batches, "text"):
            tokenizer = library_tokenizer(path, pattern)
            if writer is None:
                name = f"part-{part:06d}-{uuid.uuid4().hex}.arrow"
                writer, end = SequenceWriter(folder, name, tokenizer.dtype, length, rows), np.array([end_id], tokenizer.dtype).tobytes()
            ids = [x + end for x in tokenizer.encode_many([x or "" for x in batch.column(1).to_pylist()])]
            at = [writer.add(x) for x in ids]
            n = len(ids)
            yield pa.record_batch([batch.column(0), pa.array([name] * n), pa.array([part] * n, pa.int32()), pa.array(at, pa.int64()), pa.array([len(x) // tokenizer.dtype.itemsize for x in ids], pa.int64())], names=["doc_id", "file", "part", "offset", "n_tokens"])
        if writer:
            writer.close()

    spread = pick(docs, doc_id=doc_id, text=text)
    ordered = spread.repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    index = kept_as_table(ordered.mapInArrow(run, f"doc_id {dict(spread.dtypes)['doc_id']}, file string, part int, offset bigint, n_tokens bigint"), "token-index")
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    parts = index.groupBy("part").agg(F.sum("n_tokens").alias("n")).select("part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    return index.join(parts, "part").select("doc_id", "file", "part", "offset", "n_tokens", (F.col("base") + F.col("offset")).alias("start"))


def read_token_files(index: DataFrame, folder: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every index row, its ids read from the files."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            files, offsets, counts = (batch.column(k).to_pylist() for k in (1, 2, 3))
            crc = [zlib.crc32(sequence_reader(folder, f).run(o, n).astype("<u4").tobytes()) for f, o, n in zip(files, offsets, counts)]
            yield pa.record_batch([batch.column(0), batch.column(4), batch.column(3), pa.array(crc, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    rows = index.select("doc_id", "file", "offset", "n_tokens", "start")
    return rows.mapInArrow(run, f"doc_id {dict(rows.dtypes)['doc_id']}, start bigint, n_tokens bigint, ids_crc32 bigint")


def token_files_round_trip(docs: DataFrame, **options) -> DataFrame:
    """Writes the token files to the shared folder and reads every document back from them."""
    folder = shared_folder(docs.sparkSession, "token-files")
    return read_token_files(write_token_files(docs, folder, **options), folder)
