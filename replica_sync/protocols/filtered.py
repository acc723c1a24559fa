"""Protocols that first split both states by membership filters; what the filters hide is then reconciled exactly."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace
from functools import reduce, wraps

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from replica_sync.functions.wire import SyncConfig
from replica_sync.operators.buckets import bucket_digests, mismatched
from replica_sync.operators.membership import build_filter, filter_bytes, probed
from replica_sync.protocols.base import PART, Replicas, SyncResult, Transcript, by_segment, merged, owned, picked, protocol, reconcile, sizes, times, without
from replica_sync.protocols.exact import bucket_reconciled, bucketed, bucketed_rateless, by_bucket, counts_by, digests_of, in_buckets, rateless
from replica_sync.sources.tables import placed, snapshot


KNOWN = ["sid", "seg", "nbytes", "h", "d", "d2"]


@dataclass
class Split:
    """Both filters, and each side's perhaps common and certainly exclusive parts, without payloads."""

    filter_a: DataFrame
    filter_b: DataFrame
    com_a: DataFrame
    excl_a: DataFrame
    com_b: DataFrame
    excl_b: DataFrame


def filter_split(r: Replicas) -> Split:
    """B splits by A's filter, then A by B's filter over B's perhaps common parts. Each part is probed once."""
    filter_a = snapshot(build_filter(r.a, r.sessions), "filter-a")
    b = by_segment(probed(r.b.select(*KNOWN), filter_a), "split-b")
    filter_b = snapshot(build_filter(b.where("hit"), r.sessions), "filter-b")
    a = by_segment(probed(r.a.select(*KNOWN), filter_b), "split-a")
    return Split(filter_a, filter_b, *(x.where(f"hit = {hit}").drop("hit") for x in (a, b) for hit in ("true", "false")))


def whole(parts: DataFrame, *chosen: DataFrame) -> DataFrame:
    """The chosen parts with their payloads."""
    keys = reduce(DataFrame.unionByName, [c.select("sid", "seg", "h") for c in chosen])
    return parts.join(keys, ["sid", "seg", "h"], "left_semi").select(*PART)


def unless_unfiltered(plain: Callable[..., SyncResult] | None) -> Callable:
    """A share of 0 false positives stands for no filter at all: sessions of that kind run the protocol without filters."""

    def wrap(run: Callable[[Replicas, SyncConfig], SyncResult]) -> Callable[..., SyncResult]:
        @protocol
        @wraps(run)
        def wrapped(r: Replicas, cfg: SyncConfig) -> SyncResult:
            shares = {row["sid"]: row["eps"] for row in r.sessions.select("sid", "eps").collect()}  # as many as sessions
            bare = [sid for sid, eps in shares.items() if eps == 0]
            if not bare:
                return run(r, cfg)
            if plain is None:
                raise ValueError("filters alone need a share of false positives above 0")
            only = lambda sids: Replicas(*(x.where(F.col("sid").isin(sids)) for x in (r.a, r.b, r.sessions)))
            first = plain(only(bare), replace(cfg, eps=None))
            transcript = first.transcript.withColumn("protocol", F.lit(run.__name__))
            rest = [sid for sid in shares if sid not in bare]
            if not rest:
                return SyncResult(run.__name__, first.state_a, first.state_b, transcript, first.details)
            second = run(only(rest), cfg)
            return SyncResult(run.__name__, first.state_a.unionByName(second.state_a), first.state_b.unionByName(second.state_b), transcript.unionByName(second.transcript), second.details)

        return wrapped

    return wrap


@unless_unfiltered(None)
def filter_only(r: Replicas, cfg: SyncConfig) -> SyncResult:
    """Filters alone: false positives stay apart, so the states need not meet."""
    r = r.by_segment()
    s = filter_split(r)
    log = Transcript("filter_only", r.sessions)
    log.add("A", "filter", metadata=[filter_bytes(s.filter_a)])
    log.add("B", "filter_and_exclusive", s.excl_b, r.a, [filter_bytes(s.filter_b)])
    log.add("A", "exclusive", s.excl_a, r.b)
    state_a, state_b = merged(r.a, whole(r.b, s.excl_b)), merged(r.b, whole(r.a, s.excl_a))
    missing = without(state_b, state_a).withColumn("lacks", F.lit("a")).unionByName(without(state_a, state_b).withColumn("lacks", F.lit("b")))
    return SyncResult("filter_only", state_a, state_b, log.table(), missing)


def known_to(replica: DataFrame, *arrived: DataFrame) -> DataFrame:
    """What a side can tell apart after messages: its own parts and those that came."""
    return reduce(DataFrame.unionByName, [x.select("sid", "seg", "h") for x in (replica, *arrived)])


@unless_unfiltered(bucketed)
def filter_bucketed(r: Replicas, cfg: SyncConfig) -> SyncResult:
    """Filters, then bucket digests over the perhaps common parts; B's answer opens the buckets."""
    r = r.by_segment()
    s = filter_split(r)
    counts = snapshot(counts_by(s.com_b, r.sessions), "counts")
    a, b = by_bucket(s.com_a, counts), by_bucket(s.com_b, counts)
    bad = placed(mismatched(bucket_digests(a), bucket_digests(b)), ["sid", "bucket"], name="mismatched")
    log = Transcript("filter_bucketed", r.sessions)
    log.add("A", "filter", metadata=[filter_bytes(s.filter_a)])
    log.add("B", "filter_exclusive_digests", s.excl_b, r.a, [filter_bytes(s.filter_b), times(counts, "n_buckets", cfg.wire.digest)])
    return opened(r, s, a, b, bad, log, cfg)


def opened(r: Replicas, s: Split, a: DataFrame, b: DataFrame, bad: DataFrame, log: Transcript, cfg: SyncConfig) -> SyncResult:
    """A sends its exclusive parts and its mismatched buckets whole; B answers with what those lack."""
    opened_a = in_buckets(a, bad)
    sent = opened_a.select(*KNOWN)
    log.add("A", "exclusive_and_buckets", s.excl_a.select(*KNOWN).unionByName(sent), r.b, [times(sizes(bad), "n", cfg.wire.bucket_index)])
    rest = without(in_buckets(b, bad), opened_a).select(*KNOWN)
    log.add("B", "missing_state", rest, known_to(r.a, s.excl_b))
    return SyncResult(log.protocol, merged(r.a, whole(r.b, s.excl_b, rest)), merged(r.b, whole(r.a, s.excl_a, sent)), log.table(), bad)


@unless_unfiltered(rateless)
def filter_rateless(r: Replicas, cfg: SyncConfig) -> SyncResult:
    """Filters, then B streams cells over its perhaps common digests; A decodes and both send their false positives."""
    r = r.by_segment()
    s = filter_split(r)
    found = reconcile(digests_of(s.com_a), digests_of(s.com_b), cfg)
    log = Transcript("filter_rateless", r.sessions)
    log.add("A", "filter", metadata=[filter_bytes(s.filter_a)])
    log.add("B", "init_stream", s.excl_b, r.a, [filter_bytes(s.filter_b)])
    log.add("B", "cells", metadata=found.costs(cfg.wire))
    hidden_a = picked(s.com_a, found, "a_only")
    log.add("A", "end_of_stream", s.excl_a.unionByName(hidden_a), r.b, [times(owned(found, "b_only"), "n", cfg.wire.digest)])
    hidden_b = picked(s.com_b, found, "b_only")
    log.add("B", "missing_hidden", hidden_b, known_to(r.a, s.excl_b))
    return SyncResult("filter_rateless", merged(r.a, whole(r.b, s.excl_b, hidden_b)), merged(r.b, whole(r.a, s.excl_a, hidden_a)), log.table(), found.rows)


@unless_unfiltered(bucketed_rateless)
def filter_bucketed_rateless(r: Replicas, cfg: SyncConfig) -> SyncResult:
    """Filters, then coded cells over the digests of buckets of the perhaps common parts."""
    r = r.by_segment()
    s = filter_split(r)
    counts = snapshot(counts_by(s.com_b, r.sessions), "counts")
    a, b = by_bucket(s.com_a, counts), by_bucket(s.com_b, counts)
    bad, found = bucket_reconciled(a, b, counts, cfg)
    log = Transcript("filter_bucketed_rateless", r.sessions)
    log.add("A", "filter", metadata=[filter_bytes(s.filter_a)])
    log.add("B", "init_stream", s.excl_b, r.a, [filter_bytes(s.filter_b)])
    log.add("B", "cells", metadata=found.costs(cfg.wire))
    return opened(r, s, a, b, placed(bad, ["sid", "bucket"], name="mismatched"), log, cfg)
