"""One object for users: replicas by name, synchronise, compare, advise, explain."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from replica_sync.functions import catalog
from replica_sync.functions.digest import with_digest
from replica_sync.functions.wire import SyncConfig
from replica_sync.plans.costmodel import Advice, advise
from replica_sync.plans.metrics import converged, summarise
from replica_sync.protocols import PROTOCOLS, Replicas, SyncResult
from replica_sync.related.estimators import estimate_difference
from replica_sync.sources import tables


def synchronize(a: DataFrame, b: DataFrame, protocol: str = "filter_rateless", cfg: SyncConfig | None = None) -> SyncResult:
    """Synchronises two tables with a payload column; "auto" asks the cost model with an estimated similarity."""
    cfg = cfg or SyncConfig()
    sides = []
    for side in (a, b):
        parts = side if "h" in side.columns else with_digest(side.select("payload").distinct().withColumn("nbytes", F.octet_length("payload")), segments=cfg.segments or 1)
        sides.append(parts)
    if protocol == "auto":
        chosen = advice_for(*sides, cfg)
        protocol = chosen.protocol
        cfg = replace(cfg, eps=chosen.eps if 0 < chosen.eps < 1 else cfg.eps)
    return PROTOCOLS[protocol](Replicas.single(*sides, cfg), cfg)


def advice_for(a: DataFrame, b: DataFrame, cfg: SyncConfig | None = None) -> Advice:
    estimate = estimate_difference(a, b, "theta").first()
    mean = a.agg(F.avg("nbytes")).first()[0] or 1.0
    return advise(min(1.0, max(0.0, estimate["similarity"])), max(1.0, estimate["card_a"]), cfg, mean)


class SyncSession:
    """Named replicas over one Spark session and one configuration."""

    def __init__(self, spark: SparkSession, cfg: SyncConfig | None = None):
        self.spark, self.cfg, self.replicas = spark, cfg or SyncConfig(), {}
        catalog.register(spark)

    def replica(self, name: str, payloads: DataFrame) -> DataFrame:
        """Keeps a table's payload column as a snapshot of parts under a name."""
        parts = with_digest(payloads.select("payload").distinct().withColumn("nbytes", F.octet_length("payload")), segments=self.cfg.segments or 1)
        self.replicas[name] = tables.snapshot(parts, f"replica-{name}")
        return self.replicas[name]

    def synchronize(self, a: str, b: str, protocol: str = "filter_rateless") -> SyncResult:
        """Synchronises two replicas and keeps their new states."""
        result = synchronize(self.replicas[a], self.replicas[b], protocol, self.cfg)
        for name, state in ((a, result.state_a), (b, result.state_b)):
            self.replicas[name] = tables.snapshot(state.drop("sid"), f"replica-{name}")
        return result

    def compare(self, a: str, b: str, protocols: list[str] | None = None) -> DataFrame:
        """METRIC rows of several protocols on the same replicas, whose states stay as they are."""
        out = None
        for protocol in protocols or [p for p in PROTOCOLS if p != "filter_only"]:
            result = synchronize(self.replicas[a], self.replicas[b], protocol, self.cfg)
            row = tables.snapshot(summarise(result.transcript).join(converged(result), "sid").drop("sid"), "compare")
            out = row if out is None else out.unionByName(row)
        return out

    def advise(self, a: str, b: str) -> Advice:
        return advice_for(self.replicas[a], self.replicas[b], self.cfg)

    def explain_sync(self, a: str, b: str, protocol: str = "filter_rateless") -> str:
        """The physical plan that makes the transcript."""
        result = synchronize(self.replicas[a], self.replicas[b], protocol, self.cfg)
        return self.spark._jvm.PythonSQLUtils.explainString(result.transcript._jdf.queryExecution(), "formatted")
