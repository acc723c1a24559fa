"""The experiment workloads: sweeps over similarity and settings, all sessions of a protocol in one run."""

from __future__ import annotations

from itertools import product

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from replica_sync.functions.digest import segment_of
from replica_sync.functions.wire import SyncConfig, segments_for
from replica_sync.plans.metrics import summarise
from replica_sync.protocols import PROTOCOLS, Replicas, SyncResult
from replica_sync.protocols.base import PART
from replica_sync.sources import replicas, tables

SIMILARITIES = [0.0, 0.05, 0.25, 0.45, 0.5, 0.75, 0.9, 0.93, 0.95, 0.99, 1.0]
EPS = [0.001, 0.01, 0.02, 0.05, 0.25]
LOAD_FACTORS = [0.2, 1.0, 5.0]
USES = {"state_driven": (), "bucketed": ("f",), "filter_only": ("eps",), "filter_bucketed": ("eps", "f"), "rateless": (), "filter_rateless": ("eps",), "bucketed_rateless": ("f",), "filter_bucketed_rateless": ("eps", "f")}


def sessions(spark: SparkSession, protocol: str, similarities: list[float], eps: list[float], load_factors: list[float]) -> list[tuple[int, float, float, float]]:
    """(sid, s, eps, load_factor): parameters that a protocol does not use do not multiply its sessions."""
    uses = USES[protocol]
    combos = product(similarities, eps if "eps" in uses else eps[:1], load_factors if "f" in uses else load_factors[:1])
    return [(i, float(s), float(e), float(f)) for i, (s, e, f) in enumerate(combos)]


def parameters(spark: SparkSession, rows: list[tuple[int, float, float, float]]) -> DataFrame:
    """The sessions' rows as literals of the plan."""
    values = ", ".join(f"({sid}L, {s!r}D, {e!r}D, {f!r}D)" for sid, s, e, f in rows)
    return spark.sql(f"select * from values {values} as t(sid, s, eps, load_factor)")


#: Parts on both sides of all sessions that are under way at once in a sweep.
SWEPT_PARTS = 12_000_000


def replicas_for(parts: DataFrame, rows: list[tuple[int, float, float, float]], cfg: SyncConfig, c: int | None = None) -> Replicas:
    """Both sides of every session: ranked parts, crossed with the sessions' parameters."""
    spark = parts.sparkSession
    table = parameters(spark, rows)
    crossed = parts.crossJoin(F.broadcast(table.select("sid", "s")))  # as many rows as sessions
    each = c if c is not None else (parts.agg(F.max("size")).first()[0] or 0) // 2
    pair = replicas.sided(crossed, F.col("s"), c).withColumn("seg", segment_of(cfg.segments or segments_for(each)))
    a, b = replicas.sides(pair.select(*PART, "side"))  # protocols place them as they need
    return Replicas(a, b, table.select("sid", "eps", "load_factor"))


def compared(parts: DataFrame, protocol: str, rows: list[tuple[int, float, float, float]], cfg: SyncConfig, c: int | None = None) -> tuple[SyncResult, DataFrame]:
    """The result over the given sessions, and their parameters."""
    table = parameters(parts.sparkSession, rows)
    return PROTOCOLS[protocol](replicas_for(parts, rows, cfg, c), cfg), table


def run(parts: DataFrame, protocol: str, similarities: list[float], eps: list[float] = (0.01,), load_factors: list[float] = (1.0,), cfg: SyncConfig | None = None, c: int | None = None) -> tuple[SyncResult, DataFrame]:
    """The result over all sessions, and their parameters."""
    cfg = cfg or SyncConfig()
    return compared(parts, protocol, sessions(parts.sparkSession, protocol, list(similarities), list(eps), list(load_factors)), cfg, c)


def sweep(parts: DataFrame, protocols: list[str], similarities: list[float] = SIMILARITIES, eps: list[float] = EPS, load_factors: list[float] = LOAD_FACTORS, cfg: SyncConfig | None = None, c: int | None = None) -> DataFrame:
    """METRIC rows with s, eps, load_factor of all protocols; parameters that a protocol does not use are null.

    Bytes are counted by digests and lengths, so the parts go without their payloads; as many sessions run at once as have
    SWEPT_PARTS parts together (one at least), and their files go when their rows are written.
    """
    spark, cfg = parts.sparkSession, cfg or SyncConfig()
    ranked = tables.snapshot(replicas.ranked(parts.withColumn("payload", F.lit(None).cast("string"))), "ranked")
    each = c if c is not None else (ranked.agg(F.max("size")).first()[0] or 0) // 2
    at_once = max(1, SWEPT_PARTS // max(1, 2 * each))
    paths = []
    for protocol in protocols:
        rows = sessions(spark, protocol, list(similarities), list(eps), list(load_factors))
        for k in range(0, len(rows), at_once):
            paths.append(tables.shared_folder(spark, f"metrics-{protocol}"))
            some = rows[k : k + at_once]
            with tables.passing(spark), tables.placing(spark, len(some) * each):
                result, table = compared(ranked, protocol, some, cfg, c)
                metrics = summarise(result.transcript).join(table, "sid").drop("sid")
                for column, use in (("eps", "eps"), ("load_factor", "f")):
                    if use not in USES[protocol]:
                        metrics = metrics.withColumn(column, F.lit(None).cast("double"))
                schema = tables.snapshot(metrics.coalesce(1), path=paths[-1]).schema
                del result, table, metrics
    return spark.read.schema(schema).parquet(*paths)


def without_filters(parts: DataFrame, **options) -> DataFrame:
    return sweep(parts, ["state_driven", "bucketed", "rateless", "bucketed_rateless"], **options)


def with_filters(parts: DataFrame, **options) -> DataFrame:
    return sweep(parts, ["filter_bucketed", "filter_rateless", "filter_bucketed_rateless"], **options)


def high_similarity(parts: DataFrame, **options) -> DataFrame:
    return sweep(parts, ["rateless", "filter_rateless"], similarities=[round(0.9 + k / 100, 2) for k in range(11)], **options)


def best_four(parts: DataFrame, similarities: list[float] = SIMILARITIES, **options) -> DataFrame:
    return sweep(parts, ["state_driven", "rateless", "filter_bucketed", "filter_rateless"], similarities, [0.01], [0.2], **options)


def filter_ablation(parts: DataFrame, similarities: list[float] = SIMILARITIES, **options) -> DataFrame:
    """Each protocol with and without the filter, at 1 % and one bucket per part."""
    return sweep(parts, ["bucketed", "filter_bucketed", "rateless", "filter_rateless", "bucketed_rateless", "filter_bucketed_rateless"], similarities, [0.01], [1.0], **options)


def bucket_ablation(parts: DataFrame, similarities: list[float] = SIMILARITIES, **options) -> DataFrame:
    return sweep(parts, ["filter_rateless", "filter_bucketed_rateless"], similarities, [0.01], LOAD_FACTORS, **options)


def redundancy_by_load(parts: DataFrame, **options) -> DataFrame:
    """Buckets alone over many similarities: where redundancy peaks for each load factor."""
    return sweep(parts, ["bucketed"], similarities=[k / 20 for k in range(21)], **options)
