"""Protocols without filters: whole state, buckets, coded cells, coded cells over buckets."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from replica_sync.functions.digest import hex_number
from replica_sync.functions.wire import SyncConfig, segments_for
from replica_sync.operators.buckets import all_bucket_digests, bucket_count, bucket_digests, mismatched
from replica_sync.protocols.base import Difference, Replicas, SyncResult, Transcript, merged, owned, picked, protocol, reconcile, sizes, times, without
from replica_sync.sources.tables import hashed, placed, snapshot


@protocol
def state_driven(r: Replicas, cfg: SyncConfig) -> SyncResult:
    """One side ships its whole state; the other answers with what that lacks."""
    r = r.by_segment()
    log = Transcript("state_driven", r.sessions)
    log.add("A", "sync", r.a, r.b)
    lacking = without(r.b, r.a)
    log.add("B", "missing_state", lacking, r.a)
    return SyncResult("state_driven", merged(r.a, lacking), merged(r.b, r.a), log.table())


def numbered(parts: DataFrame, counts: DataFrame) -> DataFrame:
    """Parts with their bucket; counts: sid, n_buckets, as the initiator fixed it: one row a session, of which the driver has a list."""
    return parts.join(F.broadcast(counts), "sid").withColumn("bucket", (F.col("d") % F.col("n_buckets")).cast("bigint")).drop("n_buckets")


def by_bucket(parts: DataFrame, counts: DataFrame) -> DataFrame:
    return placed(numbered(parts, counts), ["sid", "bucket"], order=["bucket", "sid"])  # numbers that differ much sort fast


def counts_by(parts: DataFrame, sessions: DataFrame) -> DataFrame:
    found = sessions.select("sid", "load_factor").join(sizes(parts), "sid", "left")
    return found.select("sid", bucket_count(F.coalesce("n", F.lit(0)), F.col("load_factor")).cast("bigint").alias("n_buckets"))


def in_buckets(bucketed: DataFrame, chosen: DataFrame) -> DataFrame:
    return bucketed.join(hashed(chosen.select("sid", "bucket")), ["sid", "bucket"], "left_semi")


@protocol
def bucketed(r: Replicas, cfg: SyncConfig) -> SyncResult:
    """All bucket digests go over; mismatched buckets come back whole, and what they lack returns."""
    counts = snapshot(counts_by(r.a, r.sessions), "counts")
    a, b = by_bucket(r.a, counts), by_bucket(r.b, counts)
    bad = placed(mismatched(bucket_digests(a), bucket_digests(b)), ["sid", "bucket"])
    log = Transcript("bucketed", r.sessions)
    log.add("A", "bucket_digests", metadata=[times(counts, "n_buckets", cfg.wire.digest)])
    whole = in_buckets(b, bad)
    log.add("B", "buckets", whole, a, [times(sizes(bad), "n", cfg.wire.bucket_index)])
    rest = without(in_buckets(a, bad), whole)
    log.add("A", "missing_state", rest, b)
    return SyncResult("bucketed", merged(r.a, whole), merged(r.b, rest), log.table(), bad)


def digests_of(parts: DataFrame) -> DataFrame:
    return parts.select("sid", "seg", "d", "d2")


@protocol
def rateless(r: Replicas, cfg: SyncConfig) -> SyncResult:
    """A streams cells over its digests until B decodes; B sends its parts and asks for the others by digest."""
    r = r.by_segment()
    found = reconcile(digests_of(r.b), digests_of(r.a), cfg)  # decoded at B: a_only of the decoder is B's
    log = Transcript("rateless", r.sessions)
    log.add("A", "cells", metadata=found.costs(cfg.wire))
    ours = picked(r.b, found, "a_only")
    log.add("B", "end_of_stream", ours, r.a, [times(owned(found, "b_only"), "n", cfg.wire.digest)])
    asked = picked(r.a, found, "b_only")
    log.add("A", "missing_state", asked, r.b)
    owner = F.when(F.col("owner") == "a_only", "b_only").otherwise("a_only")
    return SyncResult("rateless", merged(r.a, ours), merged(r.b, asked), log.table(), found.rows.withColumn("owner", owner))


def bucket_reconciled(mine: DataFrame, theirs: DataFrame, counts: DataFrame, cfg: SyncConfig) -> tuple[DataFrame, Difference]:
    """Mismatched buckets found by coded cells over the digests of all buckets, decoded at the first side."""
    segments = cfg.segments or segments_for(counts.agg(F.max("n_buckets")).first()[0] or 1)

    def coded_digests(bucketed_parts: DataFrame) -> DataFrame:
        every = all_bucket_digests(bucket_digests(bucketed_parts), counts)
        rows = every.select("sid", (F.col("bucket") % segments).cast("int").alias("seg"), hex_number(F.col("digest"), 1, 15).alias("d"), hex_number(F.col("digest"), 17, 15).alias("d2"), "bucket")
        return rows.repartition("sid", "seg").sortWithinPartitions("sid", "seg")  # a task meets few segments, so their cells leave once

    own, other = (snapshot(coded_digests(x), "bucket-digests") for x in (mine, theirs))  # every slice of the stream reads both
    found = reconcile(digests_of(own), digests_of(other), cfg)
    return picked(own, found, "a_only").select("sid", "bucket"), found


@protocol
def bucketed_rateless(r: Replicas, cfg: SyncConfig) -> SyncResult:
    """As bucketed, but the digests of buckets are reconciled by coded cells: two differences per bad bucket."""
    counts = snapshot(counts_by(r.a, r.sessions), "counts")
    a, b = by_bucket(r.a, counts), by_bucket(r.b, counts)
    bad, found = bucket_reconciled(b, a, counts, cfg)
    bad = placed(bad, ["sid", "bucket"])
    log = Transcript("bucketed_rateless", r.sessions)
    log.add("A", "cells", metadata=found.costs(cfg.wire))
    whole = in_buckets(b, bad)
    log.add("B", "buckets", whole, a, [times(sizes(bad), "n", cfg.wire.bucket_index)])
    rest = without(in_buckets(a, bad), whole)
    log.add("A", "missing_state", rest, b)
    return SyncResult("bucketed_rateless", merged(r.a, whole), merged(r.b, rest), log.table(), bad)
