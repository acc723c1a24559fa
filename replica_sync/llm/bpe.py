"""Byte-level BPE by a segment tree over byte positions.

Leaf i holds the rank of merging the live token at i with its right neighbour; inner nodes hold the
smallest (rank, position), so the root names the leftmost best pair. A merge changes three leaves.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from replica_sync.llm.common import pick, small_batches, splitter

#: Pieces a worker remembers; beyond it the memory starts anew, results stay the same.
REMEMBERED = 400_000
NO_PAIR = 1 << 62


class RankTable:
    """Ranks of byte strings, ids and the splitting pattern; encode and decode whole texts."""

    def __init__(self, path: str, pattern: str):
        with open(path, "rb") as lines:
            self.rank = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, lines)}
        self.token = {rank: token for token, rank in self.rank.items()}
        self.split = splitter(pattern)
        self.known: dict[str, bytes] = {}

    def merge(self, piece: bytes) -> list[int]:
        """Ids of one piece: O(n log n) for n bytes."""
        rank = self.rank
        if (whole := rank.get(piece)) is not None:
            return [whole]
        n = len(piece)
        leaves = 1 << max(1, (n - 1).bit_length())
        shift = leaves.bit_length()
        tree = [NO_PAIR] * (2 * leaves)
        for i in range(n - 1):
            r = rank.get(piece[i : i + 2])
            if r is not None:
                tree[leaves + i] = r << shift | i
        for i in range(leaves - 1, 0, -1):
            a, b = tree[2 * i], tree[2 * i + 1]
            tree[i] = a if a < b else b
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))  # starts of the neighbours
        mask = (1 << shift) - 1

        def put(i: int, value: int) -> None:
            i += leaves
            tree[i] = value
            while i > 1:
                a, b = tree[i], tree[i ^ 1]
                i >>= 1
                least = a if a < b else b
                if tree[i] == least:
                    return
                tree[i] = least

        while (best := tree[1]) < NO_PAIR:
            i = best & mask
            gone = after[i]
            end = after[gone]
            after[i] = end
            put(gone, NO_PAIR)
            if end < n:
                before[end] = i
                r = rank.get(piece[i : after[end]])
                put(i, NO_PAIR if r is None else r << shift | i)
            else:
                put(i, NO_PAIR)
            if (left := before[i]) >= 0:
                r = rank.get(piece[left:end])
                put(left, NO_PAIR if r is None else r << shift | left)
        ids, i = [], 0
        while i < n:
            ids.append(rank[piece[i : after[i]]])
            i = after[i]
        return ids

    def encode(self, text: str) -> bytes:
        """Ids of a text as little-endian unsigned 32-bit integers."""
        pieces, known = self.split(text), self.known
        try:
            return b"".join(map(known.__getitem__, pieces))
        except KeyError:
            if len(known) > REMEMBERED:
                known.clear()
            for piece in set(pieces):
                if piece not in known:
                    known[piece] = np.array(self.merge(piece.encode()), dtype="<u4").tobytes()
            return b"".join(map(known.__getitem__, pieces))

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.token.__getitem__, np.frombuffer(ids, dtype="<u4").tolist()))


@lru_cache(maxsize=2)
def rank_table(path: str, pattern: str) -> RankTable:
    return RankTable(path, pattern)


def default_vocabulary() -> tuple[str, str]:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN


def encode_texts(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", path: str | None = None, pattern: str | None = None, keep_ids: bool = False) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 (with keep_ids also ids, as 32-bit words in a binary) of every row.

    Narrow, no shuffle. A null text counts as empty: no tokens, digests of the empty string. Repeated rows
    give repeated results, an empty table an empty one; other columns are not read. The vocabulary file is
    read on each executor by its path.
    """
    own = default_vocabulary() if path is None or pattern is None else ("", "")
    path, pattern = path or own[0], pattern or own[1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = rank_table(path, pattern)
        for batch in small_batches(batches, "text"):
            ids = [table.encode(x or "") for x in batch.column(1).to_pylist()]
            columns = {
                "doc_id": batch.column(0),
                "n_tokens": pa.array([len(x) // 4 for x in ids], pa.int64()),
                "ids_sha256": pa.array([hashlib.sha256(x).hexdigest() for x in ids]),
                "decoded_sha256": pa.array([hashlib.sha256(table.decode(x)).hexdigest() for x in ids]),
            }
            if keep_ids:
                columns["ids"] = pa.array(ids, pa.binary())
            yield pa.record_batch(list(columns.values()), names=list(columns))

    rows = pick(docs, doc_id=doc_id, text=text)
    return rows.mapInArrow(run, f"doc_id {dict(rows.dtypes)['doc_id']}, n_tokens bigint, ids_sha256 string, decoded_sha256 string" + ", ids binary" * keep_ids)


def decode_ids(encoded: DataFrame, path: str | None = None, pattern: str | None = None) -> DataFrame:
    """doc_id and text from encode_texts(..., keep_ids=True): the exact inverse."""
    own = default_vocabulary()
    path, pattern = path or own[0], pattern or own[1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = rank_table(path, pattern)
        for batch in small_batches(batches, "ids"):
            yield pa.record_batch([batch.column(0), pa.array([table.decode(x or b"").decode("utf-8", "replace") for x in batch.column(1).to_pylist()], pa.string())], names=["doc_id", "text"])

    rows = encoded.select("doc_id", "ids")
    return rows.mapInArrow(run, f"doc_id {dict(rows.dtypes)['doc_id']}, text string")
