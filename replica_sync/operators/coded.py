"""The extendable stream of invertible coded cells over a set of digests.

Cell i holds, of the digests mapped to it, the XOR, the XOR of their checks, and their number. A digest is in cell 0
and then in cells ever further apart (density 1 / (1 + i/2)). Any prefix of the stream is itself a table
from which a difference of about three quarters of its length can be recovered.

Two walks give the indices: "md5", in built-in expressions, the same in any SQL engine; and "mixed", a 64-bit
mixer in numpy over whole Arrow batches that adds the cells up before anything is exchanged.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

KEYS = ("sid", "seg")
CELL = "sid bigint, seg int, i int, id_sum bigint, check_sum bigint, cnt bigint"
CELLS = [c.split()[0] for c in CELL.split(", ")]
DIFF = "sid bigint, seg int, d bigint, owner string, used int, done boolean"
MASK = (1 << 64) - 1
# Increments and multipliers of the published split-mix generator of 64 bits.
STEP, FIRST, SECOND = 0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB


def spread(x: int) -> int:
    x = (x ^ (x >> 30)) * FIRST & MASK
    x = (x ^ (x >> 27)) * SECOND & MASK
    return x ^ (x >> 31)


def spread_all(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(FIRST)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(SECOND)
    return x ^ (x >> np.uint64(31))


def check_of(d: int) -> int:
    """60-bit check of a digest, mixed walk."""
    return spread(d ^ 0x5851F42D4C957F2D) >> 4


def checks_of(d: np.ndarray) -> np.ndarray:
    return spread_all(d ^ np.uint64(0x5851F42D4C957F2D)) >> np.uint64(4)


def next_index(i: int, draw: int) -> int:
    u = (draw >> 11) / 9007199254740992.0
    return i + max(1, math.ceil((i + 1.5) * (1.0 / math.sqrt(1.0 - u) - 1.0)))


def walk(d: int, upto: int) -> Iterator[int]:
    """Indices below upto of one digest."""
    i, state = 0, d
    while i < upto:
        yield i
        state = (state + STEP) & MASK
        i = next_index(i, spread(state))


def memberships(d: np.ndarray, low: int, high: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(rows, indices) of all digests, step by step, indices from low to below high."""
    rows = np.arange(len(d))
    at = np.zeros(len(d), dtype=np.int64)
    state = d.astype(np.uint64)
    while len(rows):
        inside = at >= low
        if inside.any():
            yield rows[inside], at[inside]
        state = state + np.uint64(STEP)
        u = (spread_all(state) >> np.uint64(11)).astype(np.float64) / 9007199254740992.0
        at = at + np.maximum(1, np.ceil((at + 1.5) * (1.0 / np.sqrt(1.0 - u) - 1.0))).astype(np.int64)
        go = at < high
        rows, at, state = rows[go], at[go], state[go]


def md5_indices(h: Column, upto: int, most: int = 96) -> Column:
    """Ascending indices below upto of a part with digest text h: the portable walk, one md5 per step."""
    empty = F.array(F.lit(0))

    def step(path: Column, n: Column) -> Column:
        last = F.element_at(path, -1)
        u = F.conv(F.substring(F.md5(F.concat(h, F.lit("#"), n.cast("string")).cast("binary")), 1, 13), 16, 10).cast("double") / F.lit(4503599627370496.0)
        jump = F.greatest(F.lit(1), F.ceil((last + 1.5) * (1.0 / F.sqrt(1.0 - u) - 1.0)))
        following = F.least(last + jump, F.lit(1 << 30)).cast("int")
        return F.when(last >= upto, path).otherwise(F.concat(path, F.array(following)))

    full = F.aggregate(F.sequence(F.lit(1), F.lit(most)), empty, step)
    return F.filter(full, lambda i: i < upto)


def md5_cells(parts: DataFrame, upto: int) -> DataFrame:
    """sid, seg, i, id_sum, check_sum, cnt by the portable walk; the check is the second half of the digest."""
    placed = parts.select(*KEYS, "d", "d2", F.explode(md5_indices(F.col("h"), upto)).alias("i"))
    return placed.groupBy(*KEYS, "i").agg(F.bit_xor("d").alias("id_sum"), F.bit_xor("d2").alias("check_sum"), F.count("*").alias("cnt"))


#: Cells that a task adds up at a time, over all its sessions and segments.
HELD_CELLS = 1 << 21


def coded_cells(digests: DataFrame, low: int, high: int, held_cells: int = HELD_CELLS) -> DataFrame:
    """Cells [low, high) over rows sid, seg, d by the mixed walk.

    Each task adds up its own cells per session and segment in numpy: at most (high - low) rows of each
    leave a task, whatever the number of parts. Where a task meets so many segments that their cells are more than held_cells, it sends
    the sums so far of those it has not met for longest; rows that lie together by segment then still leave once.
    """

    def sent(key: tuple[int, int], sums: list[np.ndarray]) -> pa.RecordBatch:
        ids, checks, count = sums
        some = np.flatnonzero(count)
        n = len(some)
        return pa.record_batch([pa.array(np.full(n, key[0])), pa.array(np.full(n, key[1], dtype=np.int32)), pa.array((some + low).astype(np.int32)), pa.array(ids[some].astype(np.int64)), pa.array(checks[some].astype(np.int64)), pa.array(count[some])], names=[c.split()[0] for c in CELL.split(", ")])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple[int, int], list[np.ndarray]] = {}  # the latest met last
        for batch in batches:
            if not batch.num_rows:
                continue
            sid, seg, d = (batch.column(k).to_numpy(zero_copy_only=False) for k in range(3))
            order = np.lexsort((seg, sid))
            sid, seg, d = sid[order], seg[order], d[order].astype(np.uint64)
            cut = np.flatnonzero((np.diff(sid) != 0) | (np.diff(seg) != 0)) + 1
            for a, b in zip([0, *cut.tolist()], [*cut.tolist(), len(d)]):
                key = (int(sid[a]), int(seg[a]))
                if key in held:
                    held[key] = held.pop(key)
                else:
                    while held and (len(held) + 1) * (high - low) > held_cells:
                        oldest = next(iter(held))
                        yield sent(oldest, held.pop(oldest))
                    held[key] = [np.zeros(high - low, dtype=np.uint64), np.zeros(high - low, dtype=np.uint64), np.zeros(high - low, dtype=np.int64)]
                ids, checks, count = held[key]
                own = d[a:b]
                check = checks_of(own)
                for rows, at in memberships(own, low, high):
                    np.bitwise_xor.at(ids, at - low, own[rows])
                    np.bitwise_xor.at(checks, at - low, check[rows])
                    np.add.at(count, at - low, 1)
        for key, sums in held.items():
            yield sent(key, sums)

    local = digests.select(F.col("sid").cast("bigint"), F.col("seg").cast("int"), "d").mapInArrow(run, CELL)
    return added(local)


def added(cells: DataFrame) -> DataFrame:
    """Cells of equal place as one."""
    return cells.groupBy(*KEYS, "i").agg(F.bit_xor("id_sum").alias("id_sum"), F.bit_xor("check_sum").alias("check_sum"), F.sum("cnt").alias("cnt"))


def subtract_cells(ours: DataFrame, theirs: DataFrame) -> DataFrame:
    """Cells of the symmetric difference: equal digests cancel, counts tell the owner (ours positive)."""
    signed = ours.select(*CELLS).unionByName(theirs.select(*CELLS[:-1], (-F.col("cnt")).alias("cnt")))
    return added(signed)


class Decoder:
    """Peels a stream of difference cells one at a time; done once cell 0, which holds every digest, is empty."""

    def __init__(self):
        self.ids: list[int] = []
        self.checks: list[int] = []
        self.counts: list[int] = []
        self.found: dict[int, int] = {}
        self.waiting: list[tuple[int, int, int]] = []  # next index, digest, state of its walk

    @property
    def done(self) -> bool:
        return bool(self.ids) and not (self.ids[0] or self.checks[0] or self.counts[0])

    def add(self, id_sum: int, check_sum: int, cnt: int) -> bool:
        i = len(self.ids)
        self.ids.append(id_sum)
        self.checks.append(check_sum)
        self.counts.append(cnt)
        while self.waiting and self.waiting[0][0] == i:
            _, d, state = heapq.heappop(self.waiting)
            self._remove(i, d, self.found[d])
            state = (state + STEP) & MASK
            heapq.heappush(self.waiting, (next_index(i, spread(state)), d, state))
        pure = [i]
        while pure:
            j = pure.pop()
            if self.counts[j] not in (1, -1) or self.checks[j] != check_of(self.ids[j]) or self.ids[j] in self.found:
                continue
            d, sign = self.ids[j], self.counts[j]
            self.found[d] = sign
            at, state = 0, d
            while at <= i:
                self._remove(at, d, sign)
                pure.append(at)
                state = (state + STEP) & MASK
                at = next_index(at, spread(state))
            heapq.heappush(self.waiting, (at, d, state))
        return self.done

    def _remove(self, i: int, d: int, sign: int) -> None:
        self.ids[i] ^= d
        self.checks[i] ^= check_of(d)
        self.counts[i] -= sign


def decoded(ids: np.ndarray, checks: np.ndarray, counts: np.ndarray) -> tuple[list[int], list[int], int, bool]:
    """Digests, their signs, cells used and whether all is decoded, by cells taken one at a time."""
    decoder, used = Decoder(), 0
    for cell in zip(ids.tolist(), checks.tolist(), counts.tolist()):
        used += 1
        if decoder.add(*cell):
            return list(decoder.found), list(decoder.found.values()), used, True
    return [], [], used, False


def shortest(rows: np.ndarray, at: np.ndarray, n: int, upto: int) -> int:
    """The shortest prefix of upto cells from which n digests can be peeled; digest rows[k] is in cell at[k], and all are in cell 0."""
    order = np.argsort(rows, kind="stable")
    places, starts = at[order].tolist(), np.searchsorted(rows[order], np.arange(n + 1)).tolist()
    holds, which = np.bincount(at, minlength=upto), np.zeros(upto, dtype=np.int64)
    np.bitwise_xor.at(which, at, rows)
    holds, which, left = holds.tolist(), which.tolist(), n
    for i in range(upto):
        if holds[i] == 1:
            pure = [i]
            while pure:
                j = pure.pop()
                if holds[j] != 1:
                    continue
                own = which[j]
                left -= 1
                for cell in places[starts[own] : starts[own + 1]]:
                    holds[cell] -= 1
                    which[cell] ^= own
                    if cell <= i and holds[cell] == 1:
                        pure.append(cell)
        if not left:
            return i + 1
    raise Incomplete(f"{left} of {n} digests are not in reach")


#: From so many cells on it pays to peel all pure cells of a round at once.
MANY_CELLS = 512


def decoded_by_rounds(ids: np.ndarray, checks: np.ndarray, counts: np.ndarray) -> tuple[list[int], list[int], int, bool]:
    """The same as decoded: rounds over all cells find the digests, and the shortest prefix follows from the cells they are in."""
    upto, found, signs, total = len(ids), [], [], 0
    x, y, n = ids.astype(np.uint64), checks.astype(np.uint64), counts.astype(np.int64)
    look = np.arange(upto)
    while len(look):
        look = look[np.abs(n[look]) == 1]
        look = look[y[look] == checks_of(x[look])]
        if not len(look):
            break
        d, first = np.unique(x[look], return_index=True)
        sign, check, met = n[look][first], checks_of(d), []
        found.append(d)
        signs.append(sign)
        total += len(d)
        if total > upto:  # a decodable stream has fewer digests than cells
            return decoded(ids, checks, counts)
        for rows, at in memberships(d, 0, upto):
            np.bitwise_xor.at(x, at, d[rows])
            np.bitwise_xor.at(y, at, check[rows])
            np.subtract.at(n, at, sign[rows])
            met.append(at)
        look = np.unique(np.concatenate(met))
    if x[0] or y[0] or n[0]:
        return [], [], upto, False
    if not total:
        return [], [], 1, True
    d, sign = np.concatenate(found), np.concatenate(signs)
    if len(np.unique(d)) < total:  # peeled twice: only a meeting of checks does that
        return decoded(ids, checks, counts)
    steps = list(memberships(d, 0, upto))
    used = shortest(*(np.concatenate([step[k] for step in steps]) for k in (0, 1)), total, upto)
    return d.astype(np.int64).tolist(), sign.tolist(), used, True


def peel(cells: DataFrame, upto: int) -> DataFrame:
    """DIFF rows of each session and segment: its recovered digests, and one row without digest that says whether it is
    done and how many cells that took: the shortest prefix that is enough.
    """

    def run(key: tuple, table: pa.Table) -> pa.Table:
        sid, seg = key[0].as_py(), key[1].as_py()
        place = table.column("i").to_numpy()
        sums = [np.zeros(upto, dtype=np.int64) for _ in range(3)]
        for x, name in zip(sums, ("id_sum", "check_sum", "cnt")):
            x[place] = table.column(name).to_numpy()
        found, signs, used, done = (decoded if upto < MANY_CELLS else decoded_by_rounds)(*sums)
        n = len(found)
        columns = [[sid] * (n + 1), [seg] * (n + 1), [*found, None], [*("a_only" if s > 0 else "b_only" for s in signs), None], [used] * (n + 1), [done] * (n + 1)]
        kinds = [pa.int64(), pa.int32(), pa.int64(), pa.string(), pa.int32(), pa.bool_()]
        return pa.table([pa.array(c, k) for c, k in zip(columns, kinds)], names=[c.split()[0] for c in DIFF.split(", ")])

    return cells.groupBy(*KEYS).applyInArrow(run, DIFF)


class Incomplete(ValueError):
    """The cells given do not hold enough to decode all differences."""


def difference_by_joins(ours: DataFrame, theirs: DataFrame, first: int = 256, growth: int = 4) -> DataFrame:
    """sid, seg, d, owner by md5 cells (sid, seg, d, d2, h on both sides), as many as it takes."""
    members, upto = ours.unionByName(theirs), first
    most = max(first, 16 * members.count())
    while True:
        try:
            return peel_by_joins(subtract_cells(md5_cells(ours, upto), md5_cells(theirs, upto)), members)
        except Incomplete:
            if upto >= most:
                raise
            upto *= growth


def peel_by_joins(cells: DataFrame, members: DataFrame) -> DataFrame:
    """The same decoding of md5 cells in relational form: rounds of finding pure cells and subtracting what they hold.

    members: sid, seg, d, d2, h of candidates on either side (each side can look up only digests it has, so
    this is a reference form for tests and small differences). Returns sid, seg, d, owner; raises Incomplete if cells are left.
    """
    upto = cells.agg(F.max("i")).first()[0] or 0
    known = members.select(F.col("sid").alias("k_sid"), F.col("seg").alias("k_seg"), "d", "d2", "h").distinct()
    found = None
    while True:
        same = (F.col("sid") == F.col("k_sid")) & (F.col("seg") == F.col("k_seg")) & (F.col("id_sum") == F.col("d")) & (F.col("check_sum") == F.col("d2"))
        pure = cells.where("abs(cnt) = 1").join(known, same).select(*KEYS, "d", "d2", "h", F.signum("cnt").cast("bigint").alias("sign")).distinct()
        rows = pure.collect()  # a round's pure cells: at most one row per cell
        if not rows:
            break
        now = pure.sparkSession.createDataFrame(rows, pure.schema)
        found = now if found is None else found.unionByName(now)
        gone = now.select(*KEYS, "d", "d2", "sign", F.explode(md5_indices(F.col("h"), upto + 1)).alias("i")).groupBy(*KEYS, "i").agg(F.bit_xor("d").alias("x"), F.bit_xor("d2").alias("y"), F.sum("sign").alias("n"))
        left = cells.join(gone, [*KEYS, "i"], "left").select(*KEYS, "i", F.col("id_sum").bitwiseXOR(F.coalesce("x", F.lit(0))).alias("id_sum"), F.col("check_sum").bitwiseXOR(F.coalesce("y", F.lit(0))).alias("check_sum"), (F.col("cnt") - F.coalesce("n", F.lit(0))).alias("cnt")).collect()
        cells = pure.sparkSession.createDataFrame(left, cells.schema)  # as many rows as cells
    left = cells.where("cnt != 0 or id_sum != 0 or check_sum != 0").count()
    if left:
        raise Incomplete(f"{left} of the cells up to {upto} are not decoded")
    if found is None:
        return members.select(*KEYS, "d").limit(0).withColumn("owner", F.lit(""))
    return found.select(*KEYS, "d", F.when(F.col("sign") > 0, "a_only").otherwise("b_only").alias("owner"))
