"""What protocols share: replicas, messages with their byte counts, and reconciliation of digest sets.

A session (sid) is one pair of replicas with its own settings; all steps carry sid as a key, so a sweep over
many similarities and settings is one run of a few plans. Each step uses the replica's own parts and what
came in messages, nothing of the other's.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace
from functools import reduce, wraps

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from replica_sync.functions.digest import segment_of
from replica_sync.functions.wire import SyncConfig, WireModel, segments_for
from replica_sync.operators import coded
from replica_sync.sources.tables import hashed, placed, snapshot

PART = ["sid", "seg", "payload", "nbytes", "h", "d", "d2"]
TRANSCRIPT = ["sid", "protocol", "seq", "sender", "kind", "metadata_bytes", "payload_bytes", "redundant_bytes", "n_items"]


@dataclass
class Replicas:
    """Parts of both sides and the sessions' settings (sid, eps, load_factor)."""

    a: DataFrame
    b: DataFrame
    sessions: DataFrame

    @classmethod
    def single(cls, a: DataFrame, b: DataFrame, cfg: SyncConfig | None = None) -> Replicas:
        """One session, number 0, of two sets of parts with digests. Parts are counted unless cfg says how many segments there are."""
        cfg = cfg or SyncConfig()
        eps, load = 0.01 if cfg.eps is None else cfg.eps, 1.0 if cfg.load_factor is None else cfg.load_factor
        one = a.sparkSession.range(1).select(F.lit(0).cast("bigint").alias("sid"), F.lit(float(eps)).alias("eps"), F.lit(float(load)).alias("load_factor"))
        segments = cfg.segments or segments_for(max(a.count(), b.count()))

        def keyed(parts: DataFrame) -> DataFrame:
            return parts.withColumn("sid", F.lit(0).cast("bigint")).withColumn("seg", segment_of(segments)).select(*PART)

        return cls(keyed(a), keyed(b), one)

    def by_segment(self) -> Replicas:
        """The same replicas, both placed by segment."""
        return replace(self, a=by_segment(self.a), b=by_segment(self.b))

    def under(self, cfg: SyncConfig) -> Replicas:
        """The same replicas with the settings that cfg gives."""
        given = {c: F.lit(float(v)) for c, v in (("eps", cfg.eps), ("load_factor", cfg.load_factor)) if v is not None}
        return replace(self, sessions=self.sessions.withColumns(given)) if given else self


@dataclass
class SyncResult:
    protocol: str
    state_a: DataFrame
    state_b: DataFrame
    transcript: DataFrame
    details: DataFrame | None = None  # what the protocol found: buckets, differences, false positives

    def states(self) -> DataFrame:
        """sid, side, payload of both final states."""
        return self.state_a.select("sid", F.lit("a").alias("side"), "payload").unionByName(self.state_b.select("sid", F.lit("b").alias("side"), "payload"))


def protocol(run: Callable[[Replicas, SyncConfig], SyncResult]) -> Callable[..., SyncResult]:
    """A protocol with the settings of its configuration, where that has any."""

    @wraps(run)
    def wrapped(r: Replicas, cfg: SyncConfig | None = None) -> SyncResult:
        cfg = cfg or SyncConfig()
        return run(r.under(cfg), cfg)

    return wrapped


def merged(*parts: DataFrame) -> DataFrame:
    """The join of sets of parts: repeated deliveries change nothing."""
    return reduce(DataFrame.unionByName, [p.select(*PART) for p in parts]).dropDuplicates(["sid", "h"])


def by_segment(parts: DataFrame, name: str = "") -> DataFrame:
    return placed(parts, ["sid", "seg"], name, ["sid", "seg"])  # a task meets few segments


def identity(parts: DataFrame, others: DataFrame) -> list[str]:
    """What tells parts apart, headed by where they lie: equal digests are in one bucket, and in one segment."""
    return ["sid", *(["bucket"] if "bucket" in parts.columns and "bucket" in others.columns else ["seg"]), "h"]


def without(parts: DataFrame, others: DataFrame) -> DataFrame:
    """The minimal difference of sets of parts: one anti join on digests."""
    keys = identity(parts, others)
    return parts.join(hashed(others.select(*keys)), keys, "left_anti").select(*parts.columns)


def within(parts: DataFrame, others: DataFrame) -> DataFrame:
    keys = identity(parts, others)
    return parts.join(hashed(others.select(*keys)), keys, "left_semi").select(*parts.columns)


def sizes(parts: DataFrame, name: str = "n") -> DataFrame:
    return parts.groupBy("sid").agg(F.count("*").alias(name))


class Transcript:
    """Messages of a protocol with what they cost."""

    def __init__(self, protocol: str, sessions: DataFrame):
        self.protocol, self.sessions, self.kinds, self.rows = protocol, sessions.select("sid"), [], []

    def add(self, sender: str, kind: str, payload: DataFrame | None = None, receiver: DataFrame | None = None, metadata: list[DataFrame] | None = None) -> None:
        """payload: the parts sent; receiver: what the other side has, for redundancy; metadata: (sid, metadata_bytes) each."""
        self.kinds.append((sender, kind))
        zero = F.lit(0).cast("bigint")

        def counted(rows: DataFrame, **of: Column) -> None:
            values = [of.get(c, zero).cast("bigint").alias(c) for c in TRANSCRIPT[5:]]
            self.rows.append(rows.select("sid", F.lit(len(self.kinds)).alias("seq"), *values))

        counted(self.sessions)  # a message that costs nothing is one too
        if payload is not None:
            counted(payload, payload_bytes=F.col("nbytes"), n_items=F.lit(1))
            if receiver is not None:
                counted(within(payload, receiver), redundant_bytes=F.col("nbytes"))
        for m in metadata or []:
            counted(m, metadata_bytes=F.col("metadata_bytes"))

    def table(self) -> DataFrame:
        """One row a session and message: all that was counted is added up in one exchange."""
        added = reduce(DataFrame.unionByName, self.rows).groupBy("sid", "seq").agg(*[F.coalesce(F.sum(c), F.lit(0)).cast("bigint").alias(c) for c in TRANSCRIPT[5:]])
        said = lambda k: F.element_at(F.array(*[F.lit(x[k]) for x in self.kinds]), F.col("seq"))
        return added.select("sid", F.lit(self.protocol).alias("protocol"), "seq", said(0).alias("sender"), said(1).alias("kind"), *TRANSCRIPT[5:])


def times(counts: DataFrame, column: str, each: int) -> DataFrame:
    """(sid, metadata_bytes): a count times the bytes of each."""
    return counts.select("sid", (F.col(column) * each).cast("bigint").alias("metadata_bytes"))


@dataclass
class Difference:
    """rows: sid, seg, d, d2, owner; used: sid, cells; told: sid, n digests that were sent whole for segments whose cells do not decode."""

    rows: DataFrame
    used: DataFrame
    told: DataFrame

    def costs(self, wire: WireModel) -> list[DataFrame]:
        return [times(self.used, "cells", wire.cell), times(self.told, "n", 2 * wire.digest)]


def expected_differences(cells: DataFrame) -> float:
    """How many digests the cells so far tell of, in the segment that has most: their counts spread as the number of digests mapped to them.

    Cell 0 has the difference of both owners' numbers, which each cell's count follows in the mean.
    """
    density = 1 / (1 + F.col("i") / 2)
    lead = cells.where("i = 0").select(*coded.KEYS, F.col("cnt").alias("lead"))
    spread = F.pow(F.col("cnt") - F.col("lead") * density, 2) / (density * (1 - density))
    found = cells.where("i > 0").join(lead, list(coded.KEYS)).groupBy(*coded.KEYS).agg(F.avg(spread).alias("n"), F.max(F.abs("lead")).alias("least"))
    return found.agg(F.max(F.greatest("n", "least"))).first()[0] or 0.0


def reconcile(ours: DataFrame, theirs: DataFrame, cfg: SyncConfig) -> Difference:
    """The symmetric difference of two digest sets (sid, seg, d, d2) by coded cells over d; owner a_only is ours.

    Slices of the stream grow by a factor, or to what the cells so far ask for; cells made before are kept, and segments
    that are decoded drop out. What is found is then checked by number and by d2: where two parts of equal d hide a difference, or a
    segment does not decode though it has more cells than both sides have digests, both sides tell each
    other all digests of that segment. The driver sees a few numbers per slice.
    """
    low, high, cells, open_, done, most, stuck = 0, cfg.first_cells, None, None, [], None, None
    keys = list(coded.KEYS)
    while True:
        x, y = ours, theirs
        if open_ is not None:
            x, y = (z.join(open_, keys, "left_semi") for z in (x, y))
            cells = cells.join(open_, keys, "left_semi")
        new = coded.subtract_cells(coded.coded_cells(x, low, high), coded.coded_cells(y, low, high))
        cells = snapshot(new if cells is None else cells.unionByName(new), "cells")
        peeled = snapshot(coded.peel(cells, high), "peeled")
        done.append(peeled.where("done"))
        open_ = snapshot(peeled.where("not done").select(*keys).distinct(), "open")
        if open_.isEmpty():
            break
        if most is None:
            most = 64 + 4 * (ours.unionByName(theirs).groupBy(*keys).count().agg(F.max("count")).first()[0] or 0)
        if high > most:
            stuck = open_
            break
        low, high = high, min(max(high * cfg.growth, int(1.6 * expected_differences(cells.join(open_, keys, "left_semi")))), max(2 * most, 2 * high))
    rows = reduce(DataFrame.unionByName, done)
    used = rows.where("d is null").groupBy("sid").agg(F.sum("used").cast("bigint").alias("cells"))
    if stuck is not None:  # all their cells were sent
        spent = stuck.groupBy("sid").agg((F.count("*") * high).alias("cells"))
        used = used.unionByName(spent).groupBy("sid").agg(F.sum("cells").alias("cells"))
    mine, other = (z.select(*keys, "d", "d2").join(rows.where(F.col("owner") == o).select(*keys, "d"), [*keys, "d"], "left_semi") for z, o in ((ours, "a_only"), (theirs, "b_only")))
    found = snapshot(mine.withColumn("owner", F.lit("a_only")).unionByName(other.withColumn("owner", F.lit("b_only"))), "difference")
    sums = lambda z, sign: z.select(*keys, "d2", F.lit(sign).alias("sign"))
    signed = sums(ours, 1).unionByName(sums(theirs, -1)).unionByName(found.select(*keys, "d2", F.when(F.col("owner") == "a_only", -1).otherwise(1).alias("sign")))
    wrong = signed.groupBy(*keys).agg(F.bit_xor("d2").alias("x"), F.sum("sign").alias("n")).where("x != 0 or n != 0").select(*keys)
    if stuck is not None:
        wrong = wrong.unionByName(stuck).distinct()
    wrong = snapshot(wrong, "told")
    if wrong.isEmpty():
        return Difference(found, used, wrong.groupBy("sid").agg(F.count("*").alias("n")))
    x, y = (z.select(*keys, "d", "d2").join(wrong, keys, "left_semi").distinct() for z in (ours, theirs))
    told = x.unionByName(y).groupBy("sid").agg(F.count("*").alias("n"))
    exact = x.withColumn("owner", F.lit("a_only")).join(y, [*keys, "d", "d2"], "left_anti").unionByName(y.withColumn("owner", F.lit("b_only")).join(x, [*keys, "d", "d2"], "left_anti"))
    return Difference(snapshot(found.join(wrong, keys, "left_anti").unionByName(exact.select(*found.columns)), "difference"), used, told)


def picked(parts: DataFrame, difference: Difference, owner: str) -> DataFrame:
    """The parts behind recovered digests of one owner."""
    wanted = difference.rows.where(F.col("owner") == owner).select("sid", "seg", "d", "d2")
    return parts.join(hashed(wanted), ["sid", "seg", "d", "d2"], "left_semi").select(*parts.columns)


def owned(difference: Difference, owner: str) -> DataFrame:
    return difference.rows.where(F.col("owner") == owner).groupBy("sid").agg(F.count("*").alias("n"))
