"""State exchange with other kinds of knowledge: none, acknowledgements, version vectors."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from replica_sync.protocols.base import Replicas, SyncResult, Transcript, merged


def full_exchange(r: Replicas) -> SyncResult:
    """Both sides ship everything."""
    log = Transcript("full_exchange", r.sessions)
    log.add("A", "state", r.a, r.b)
    log.add("B", "state", r.b, r.a)
    both = merged(r.a, r.b)
    return SyncResult("full_exchange", both, both, log.table())


def delta_shipping(log: DataFrame, acks: DataFrame, kept_from: int | None = None) -> DataFrame:
    """What a sender ships to each peer: log entries (seq, nbytes) after the peer's acknowledgement (peer, acked).

    kept_from: the log holds entries from there on only; a peer that has acknowledged less gets the full
    state, entry by entry. Returns peer, mode, n_items, nbytes.
    """
    floor = kept_from if kept_from is not None else 0
    mode = F.when(F.col("acked") + 1 < F.lit(floor), "full").otherwise("delta")
    peers = acks.select("peer", "acked", mode.alias("mode"))
    due = peers.join(log, (F.col("mode") == "full") | (F.col("seq") > F.col("acked")), "left")
    return due.groupBy("peer", "mode").agg(F.count("seq").alias("n_items"), F.coalesce(F.sum("nbytes"), F.lit(0)).cast("bigint").alias("nbytes"))


def clock_delta(state: DataFrame, clock: DataFrame) -> DataFrame:
    """The entries (replica, ctr, ...) that a version vector (replica, seen) does not cover: minimal without any digest."""
    seen = clock.select("replica", "seen")
    return state.join(seen, "replica", "left").where(F.col("ctr") > F.coalesce("seen", F.lit(-1))).drop("seen")


def version_vector(state: DataFrame) -> DataFrame:
    return state.groupBy("replica").agg(F.max("ctr").alias("seen"))
