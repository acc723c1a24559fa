"""More than two replicas: rounds of pairwise synchronisation, and one replica with several peers at once."""

from __future__ import annotations

import random

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from replica_sync.functions.digest import segment_of
from replica_sync.functions.wire import SyncConfig, segments_for
from replica_sync.protocols import PROTOCOLS, Replicas
from replica_sync.protocols.base import PART, merged
from replica_sync.sources.tables import dropped, passing, shared_folder, snapshot


def partners(names: list[str], how: str, round_: int, similarity: dict[tuple[str, str], float] | None = None, seed: int = 7, topology: dict[str, list[str]] | None = None) -> list[tuple[str, str]]:
    """Disjoint pairs of one round: at random, along a ring, along given edges in random order, or the least similar first."""
    if how == "ring":
        turned = names[round_ % 2 :] + names[: round_ % 2]
        return list(zip(turned[::2], turned[1::2]))
    free, pairs = list(names), []
    if how == "random":
        random.Random(seed * 1000 + round_).shuffle(free)
        return list(zip(free[::2], free[1::2]))
    if how == "topology":
        edges = [(a, b) for a in names for b in (topology or {}).get(a, [])]
        random.Random(seed * 1000 + round_).shuffle(edges)
    elif how == "similarity":
        edges = sorted((similarity or {}), key=lambda p: (similarity or {})[p])
    else:
        raise ValueError(f"no choice of partners {how}")
    for a, b in edges:
        if a in free and b in free and a != b:
            pairs.append((a, b))
            free.remove(a)
            free.remove(b)
    return pairs


def names_of(states: DataFrame) -> list[str]:
    """The peers, in order: as many names as replicas."""
    return sorted(r["peer"] for r in states.select("peer").distinct().collect())


def similarities(states: DataFrame) -> dict[tuple[str, str], float]:
    """Jaccard similarity of each pair of peers (peer, h); the result has one number per pair of peers."""
    sizes = {r["peer"]: r["n"] for r in states.groupBy("peer").agg(F.count("*").alias("n")).collect()}
    held = states.groupBy("h").agg(F.sort_array(F.collect_set("peer")).alias("peers")).where(F.size("peers") > 1)
    pairs = held.groupBy("peers").count().collect()  # distinct groups of peers
    shared: dict[tuple[str, str], int] = {}
    for row in pairs:
        for i, a in enumerate(row["peers"]):
            for b in row["peers"][i + 1 :]:
                shared[a, b] = shared.get((a, b), 0) + row["count"]
    names = sorted(sizes)
    return {(a, b): shared.get((a, b), 0) / max(1, sizes[a] + sizes[b] - shared.get((a, b), 0)) for i, a in enumerate(names) for b in names[i + 1 :]}


def gossip(states: DataFrame, how: str = "random", protocol: str = "filter_rateless", most_rounds: int | None = None, cfg: SyncConfig | None = None, seed: int = 7, topology: dict[str, list[str]] | None = None, payloads: bool = True) -> tuple[DataFrame, DataFrame]:
    """states: peer, payload, nbytes, h, d, d2. Rounds until all peers hold the same; all pairs of a round are sessions of one run.

    Rounds carry digests and lengths; each distinct payload is kept once and joined to the final states, unless payloads is false (the
    column is null then). A round's files go when the next states are written.

    Returns the final states and (round, pairs, total_bytes). Raises where peers still differ after most_rounds (20, or 4 a peer).
    """
    cfg = cfg or SyncConfig()
    spark = states.sparkSession
    names = names_of(states)
    whole = states.select("h").distinct().count()
    most_rounds = max(20, 4 * len(names)) if most_rounds is None else most_rounds
    segments = cfg.segments or segments_for(whole)
    eps, load = 0.01 if cfg.eps is None else cfg.eps, 1.0 if cfg.load_factor is None else cfg.load_factor
    store = snapshot(states.select("h", "payload").dropDuplicates(["h"]), "payloads") if payloads else None
    here = shared_folder(spark, "peers")
    states, log = snapshot(states.withColumn("payload", F.lit(None).cast("string")), path=here), []
    for k in range(most_rounds + 1):
        if states.groupBy("peer").agg(F.count("*").alias("n")).where(F.col("n") < whole).isEmpty():
            break
        if k == most_rounds:
            raise RuntimeError(f"peers still differ after {most_rounds} rounds of {how}")
        pairs = partners(names, how, k, similarities(states) if how == "similarity" else None, seed, topology)
        if not pairs:
            continue
        path = shared_folder(spark, "peers")
        with passing(spark):
            rows = [(i, a, b) for i, (a, b) in enumerate(pairs)]
            table = spark.createDataFrame(rows, "sid bigint, left string, right string")
            side = lambda c: states.join(table.select("sid", F.col(c).alias("peer")), "peer").withColumn("seg", segment_of(segments)).select(*PART)
            sessions = table.select("sid", F.lit(eps).alias("eps"), F.lit(load).alias("load_factor"))
            result = PROTOCOLS[protocol](Replicas(side("left"), side("right"), sessions), cfg)
            log.append((k + 1, len(pairs), result.transcript.agg(F.sum(F.col("metadata_bytes") + F.col("payload_bytes"))).first()[0]))
            moved = [result.state_a.join(table.select("sid", F.col("left").alias("peer")), "sid"), result.state_b.join(table.select("sid", F.col("right").alias("peer")), "sid")]
            idle = states.join(table.select(F.explode(F.array("left", "right")).alias("peer")), "peer", "left_anti")
            columns = ["peer", "payload", "nbytes", "h", "d", "d2"]
            after = snapshot(moved[0].select(*columns).unionByName(moved[1].select(*columns)).unionByName(idle.select(*columns)), path=path)
            del result, moved, idle
        states, before, here = after, here, path
        dropped(spark, before)
    if store is not None:
        states = states.drop("payload").join(store, "h").select("peer", "payload", "nbytes", "h", "d", "d2")
    return states, spark.createDataFrame(log, "round int, pairs int, total_bytes bigint")


def sync_many(center: DataFrame, peers: DataFrame, protocol: str = "rateless", cfg: SyncConfig | None = None) -> tuple[DataFrame, DataFrame]:
    """One replica against all peers (peer, ...) at once: the center's new state, and METRIC bytes per peer.

    Every peer is a session; the center joins what all of them had.
    """
    cfg = cfg or SyncConfig()
    names = names_of(peers)
    table = center.sparkSession.createDataFrame(list(enumerate(names)), "sid bigint, peer string")
    eps, load = 0.01 if cfg.eps is None else cfg.eps, 1.0 if cfg.load_factor is None else cfg.load_factor
    seg = segment_of(cfg.segments or segments_for(center.count()))
    mine = center.crossJoin(F.broadcast(table.select("sid"))).withColumn("seg", seg).select(*PART)  # one row per peer
    theirs = peers.join(table, "peer").withColumn("seg", seg).select(*PART)
    sessions = table.select("sid", F.lit(eps).alias("eps"), F.lit(load).alias("load_factor"))
    result = PROTOCOLS[protocol](Replicas(mine, theirs, sessions), cfg)
    joined = merged(result.state_a.withColumn("sid", F.lit(0).cast("bigint")))
    costs = result.transcript.join(table, "sid").groupBy("peer").agg(F.sum(F.col("metadata_bytes") + F.col("payload_bytes")).alias("total_bytes"))
    return joined.drop("sid", "seg"), costs
