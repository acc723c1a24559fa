"""Closed-form bytes of each protocol, the filter setting with the least metadata, and advice from an estimate."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from replica_sync.functions.wire import SyncConfig, WireModel

#: Coded cells per recovered difference in long streams, and the sum of squares that sizes optimal filters.
CELLS_PER_DIFFERENCE = 1.35
FILTER_DIVISOR = 8 * math.log(2) ** 2


def filter_bytes_per_part(eps: Column) -> Column:
    return -F.ln(eps) / F.lit(FILTER_DIVISOR)


def predicted(grid: DataFrame, wire: WireModel | None = None, rho: float = CELLS_PER_DIFFERENCE) -> DataFrame:
    """grid: s, eps, load_factor, c (parts a side), mbar (mean bytes). Adds total bytes of every protocol.

    Expectations: with e parts exclusive to each side and N buckets, N (1 - exp(-2e/N)) of them differ.
    """
    wire = wire or WireModel()
    c, mbar, eps, f = (F.col(x) for x in ("c", "mbar", "eps", "load_factor"))
    shared = 2 * F.col("s") * c / (1 + F.col("s"))
    rows = grid.withColumn("n", shared).withColumn("e", c - shared)
    n, e = F.col("n"), F.col("e")
    buckets = F.greatest(f * c, F.lit(1.0))
    bad = buckets * (1 - F.exp(-2 * e / buckets))
    com = n + eps * e
    filters = filter_bytes_per_part(eps) * (c + com)
    com_buckets = F.greatest(f * com, F.lit(1.0))
    com_bad = com_buckets * (1 - F.exp(-2 * eps * e / com_buckets))
    required = 2 * e * mbar
    # shared parts that lie in a bad bucket travel for nothing
    redundant = n * (1 - F.exp(-2 * e / buckets)) * mbar
    com_redundant = n * (1 - F.exp(-2 * eps * e / com_buckets)) * mbar
    totals = {
        "state_driven": n * mbar + required,
        "bucketed": buckets * wire.digest + bad * wire.bucket_index + redundant + required,
        "filter_bucketed": filters + com_buckets * wire.digest + com_bad * wire.bucket_index + com_redundant + required,
        "rateless": rho * 2 * e * wire.cell + e * wire.digest + required,
        "filter_rateless": filters + rho * 2 * eps * e * wire.cell + eps * e * wire.digest + required,
        "bucketed_rateless": rho * 2 * bad * wire.cell + bad * wire.bucket_index + redundant + required,
        "filter_bucketed_rateless": filters + rho * 2 * com_bad * wire.cell + com_bad * wire.bucket_index + com_redundant + required,
    }
    return rows.select("*", *[v.alias(k) for k, v in totals.items()]).drop("n", "e")


def combined(base: DataFrame, similarities: list[float], eps: list[float], load_factors: list[float]) -> DataFrame:
    """base (c, mbar) with all combinations of the parameters, as a cross join of short literal lists."""
    for name, values in (("s", similarities), ("eps", eps), ("load_factor", load_factors)):
        base = base.select("*", F.explode(F.array(*[F.lit(float(v)) for v in values])).alias(name))
    return base


def grid(spark: SparkSession, similarities: list[float], eps: list[float], load_factors: list[float], c: int = 100_000, mbar: float = 42.5) -> DataFrame:
    """All combinations of the parameters for replicas of a given size."""
    return combined(spark.range(1).select(F.lit(float(c)).alias("c"), F.lit(float(mbar)).alias("mbar")), similarities, eps, load_factors)


def measured(items: DataFrame) -> DataFrame:
    """One row c, mbar: half of the items (nbytes) a side, as pairs of replicas are drawn, and their mean bytes."""
    return items.agg(F.floor(F.count("*") / 2).cast("double").alias("c"), F.coalesce(F.avg("nbytes"), F.lit(0.0)).alias("mbar"))


def optimal_eps_of(s: Column, c: Column, wire: WireModel | None = None, rho: float = CELLS_PER_DIFFERENCE) -> Column:
    """optimal_eps over columns."""
    wire = wire or WireModel()
    n = 2 * s * c / (1 + s)
    e = c - n
    return F.when(e <= 0, F.lit(1.0)).otherwise(F.least(F.lit(1.0), (c + n) / (F.lit(FILTER_DIVISOR) * e * F.lit(2 * rho * wire.cell + wire.digest))))


def optimal_eps(s: float, c: float = 100_000.0, wire: WireModel | None = None, rho: float = CELLS_PER_DIFFERENCE) -> float:
    """The share of false positives with the least metadata of filter_rateless; 1 means no filter at all."""
    wire = wire or WireModel()
    n = 2 * s * c / (1 + s)
    e = c - n
    if e <= 0:
        return 1.0
    return min(1.0, (c + n) / (FILTER_DIVISOR * e * (2 * rho * wire.cell + wire.digest)))


@dataclass(frozen=True)
class Advice:
    protocol: str
    eps: float


def advise(similarity: float, c: float = 100_000.0, cfg: SyncConfig | None = None, mbar: float = 42.5) -> Advice:
    """Protocol and filter setting for an estimated similarity: the cheapest of whole state, cells alone, and filter with cells."""
    cfg = cfg or SyncConfig()
    n = 2 * similarity * c / (1 + similarity)
    e = c - n
    rho = CELLS_PER_DIFFERENCE
    eps = optimal_eps(similarity, c, cfg.wire)
    cost = {"state_driven": n * mbar, "rateless": e * (2 * rho * cfg.wire.cell + cfg.wire.digest)}
    if eps < 1:
        cost["filter_rateless"] = -math.log(eps) / FILTER_DIVISOR * (c + n + eps * e) + eps * e * (2 * rho * cfg.wire.cell + cfg.wire.digest)
    best = min(cost, key=cost.get)
    return Advice(best, eps if best == "filter_rateless" else 1.0)
