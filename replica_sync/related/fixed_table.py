"""Invertible tables of a fixed size: k cells per digest, sizes chosen from an estimate, restarts when decoding fails."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from replica_sync.functions.wire import SyncConfig
from replica_sync.operators import coded
from replica_sync.protocols.base import Replicas, SyncResult, Transcript, merged, picked
from replica_sync.protocols.base import Difference
from replica_sync.protocols.filtered import filter_split
from replica_sync.protocols.exact import digests_of
from replica_sync.sources.tables import snapshot


def table_cells(digests: DataFrame, cells: int, k: int = 4) -> DataFrame:
    """sid, seg, i, id_sum, check_sum, cnt: the j-th cell of a digest lies in the j-th of k equal parts of the table.

    All in built-in expressions on d and d2, so that any SQL engine gives the same cells.
    """
    width = max(1, cells // k)
    spots = F.array(*[F.lit(j * width).cast("bigint") + (F.col("d") % F.lit(1_000_003 + 2 * j) + F.col("d2") % F.lit(999_983 - 2 * j)) % F.lit(width) for j in range(k)])
    placed = digests.select("sid", "seg", "d", "d2", F.explode(spots).alias("i"))
    return placed.groupBy("sid", "seg", F.col("i").cast("int").alias("i")).agg(F.bit_xor("d").alias("id_sum"), F.bit_xor("d2").alias("check_sum"), F.count("*").alias("cnt"))


def mixed_spots(d: int, width: int, k: int) -> list[int]:
    return [j * width + coded.spread(d ^ (j + 1) * coded.STEP & coded.MASK) % width for j in range(k)]


def mixed_cells(digests: DataFrame, cells: int, k: int = 4) -> DataFrame:
    """The same table with checks that a decoder can recompute, added up per task in numpy."""
    width = max(1, cells // k)

    def run(batches):
        for batch in batches:
            d = batch.column(2).to_numpy(zero_copy_only=False).astype(np.uint64)
            check = coded.checks_of(d).astype(np.int64)
            for j in range(k):
                at = j * width + (coded.spread_all(d ^ np.uint64((j + 1) * coded.STEP & coded.MASK)) % np.uint64(width)).astype(np.int32)
                yield pa.record_batch([batch.column(0), batch.column(1), pa.array(at.astype(np.int32)), pa.array(d.astype(np.int64)), pa.array(check), pa.array(np.ones(len(d), dtype=np.int64))], names=[c.split()[0] for c in coded.CELL.split(", ")])

    rows = digests.select(F.col("sid").cast("bigint"), F.col("seg").cast("int"), "d").mapInArrow(run, coded.CELL)
    return rows.groupBy("sid", "seg", "i").agg(F.bit_xor("id_sum").alias("id_sum"), F.bit_xor("check_sum").alias("check_sum"), F.sum("cnt").alias("cnt"))


def peel_table(cells: DataFrame, size: int, k: int = 4) -> DataFrame:
    """DIFF rows of fixed tables; done says whether everything came out."""
    width = max(1, size // k)

    def run(key: tuple, table: pa.Table) -> pa.Table:
        ids, checks, counts = {}, {}, {}
        for i, a, b, c in zip(*(table.column(n).to_pylist() for n in ("i", "id_sum", "check_sum", "cnt"))):
            ids[i], checks[i], counts[i] = a, b, c
        queue, found = list(ids), {}
        while queue:
            i = queue.pop()
            if counts.get(i) not in (1, -1) or checks[i] != coded.check_of(ids[i]) or ids[i] in found:
                continue
            d, sign = ids[i], counts[i]
            found[d] = sign
            for j in mixed_spots(d, width, k):
                ids[j], checks[j], counts[j] = ids.get(j, 0) ^ d, checks.get(j, 0) ^ coded.check_of(d), counts.get(j, 0) - sign
                queue.append(j)
        done = not any(ids[i] or counts[i] for i in ids)
        rows = list(found.items()) if done else []
        n = len(rows)
        columns = [[key[0].as_py()] * (n + 1), [key[1].as_py()] * (n + 1), [*(d for d, _ in rows), None], [*("a_only" if s > 0 else "b_only" for _, s in rows), None], [width * k] * (n + 1), [done] * (n + 1)]
        kinds = [pa.int64(), pa.int32(), pa.int64(), pa.string(), pa.int32(), pa.bool_()]
        return pa.table([pa.array(c, t) for c, t in zip(columns, kinds)], names=[c.split()[0] for c in coded.DIFF.split(", ")])

    return cells.groupBy("sid", "seg").applyInArrow(run, coded.DIFF)


def fixed_table_attempt(ours: DataFrame, theirs: DataFrame, cells: int, k: int = 4) -> DataFrame:
    return peel_table(coded.subtract_cells(mixed_cells(ours, cells, k), mixed_cells(theirs, cells, k)), cells, k)


def with_restarts(ours: DataFrame, theirs: DataFrame, first: int, growth: float = 2.0, k: int = 4, most: int = 20) -> tuple[Difference, int]:
    """(difference, attempts). Each session and segment has a table of its own; those that fail are sent again, larger.

    used of the difference counts all cells sent, those of failed attempts too.
    """
    size, rows, sent = first, None, None
    for attempt in range(1, most + 1):
        peeled = snapshot(fixed_table_attempt(ours, theirs, size, k), "fixed-table")
        tables = peeled.where("d is null").select("sid", "seg", "used", "done")
        found = peeled.where("d is not null").select("sid", "seg", "d", "owner").join(ours.unionByName(theirs).distinct(), ["sid", "seg", "d"])
        rows = found if rows is None else rows.unionByName(found)
        sent = tables if sent is None else sent.unionByName(tables)
        failed = tables.where("not done").select("sid", "seg")
        if failed.isEmpty():
            used = sent.groupBy("sid").agg(F.sum("used").cast("bigint").alias("cells"))
            return Difference(rows, used, used.limit(0).select("sid", F.col("cells").alias("n"))), attempt
        ours, theirs = (x.join(failed, ["sid", "seg"], "left_semi") for x in (ours, theirs))
        size = int(size * growth)
    raise RuntimeError(f"a table of {size} cells still does not decode")


def fixed_table_reconcile(r: Replicas, first: int, cfg: SyncConfig | None = None, growth: float = 2.0) -> SyncResult:
    """As rateless, but by tables of fixed sizes with restarts."""
    cfg = cfg or SyncConfig()
    found, _ = with_restarts(digests_of(r.b), digests_of(r.a), first, growth)
    log = Transcript("fixed_table", r.sessions)
    log.add("A", "cells", metadata=found.costs(cfg.wire))
    ours, asked = picked(r.b, found, "a_only"), picked(r.a, found, "b_only")
    log.add("B", "end_of_stream", ours, r.a, [found.rows.where("owner = 'b_only'").groupBy("sid").agg((F.count("*") * cfg.wire.digest).alias("metadata_bytes"))])
    log.add("A", "missing_state", asked, r.b)
    return SyncResult("fixed_table", merged(r.a, ours), merged(r.b, asked), log.table(), found.rows)


def filter_fixed_table(r: Replicas, slack: float = 1.5, k: int = 4) -> DataFrame:
    """Filters, then one fixed table a segment, sized for the false positives expected in the fullest one: sid, seg, cells, done. It may fail."""
    s = filter_split(r)
    fullest = r.a.groupBy("sid", "seg").count().join(r.sessions.select("sid", "eps"), "sid").agg(F.max(F.col("count") * F.col("eps"))).first()[0]
    cells = max(4 * k, int(slack * 2 * (fullest or 0.0)))
    peeled = fixed_table_attempt(digests_of(s.com_a), digests_of(s.com_b), cells, k)
    return peeled.where("d is null").select("sid", "seg", F.col("used").alias("cells"), "done")


def failure_rate(r: Replicas, slacks: list[float], k: int = 4) -> DataFrame:
    """slack, tables, failed, failure_rate: each segment of each session is a trial."""
    out = None
    for slack in slacks:
        row = filter_fixed_table(r, slack, k).agg(F.lit(slack).alias("slack"), F.count("*").alias("tables"), F.count_if(~F.col("done")).alias("failed"))
        out = row if out is None else out.unionByName(row)
    return out.withColumn("failure_rate", F.try_divide("failed", "tables"))
