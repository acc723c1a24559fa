"""Estimates of the difference of two digest sets before it is known."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def bottom_k(a: DataFrame, b: DataFrame, k: int = 256) -> DataFrame:
    """One row: similarity from the k smallest digests of the union. Each side sends k digests.

    The smallest k are found by a bounded top-k per task, not by a sort.
    """
    low = lambda x: x.select(F.col("d2").alias("d")).orderBy("d").limit(k)
    both = low(a).withColumn("x", F.lit(1)).unionByName(low(b).withColumn("x", F.lit(2))).groupBy("d").agg(F.bit_or("x").alias("x"))
    return both.orderBy("d").limit(k).agg((F.count_if(F.col("x") == 3) / F.greatest(F.count("*"), F.lit(1))).alias("similarity"), F.count("*").alias("k"))


def theta(a: DataFrame, b: DataFrame, lg: int = 12) -> DataFrame:
    """One row from theta sketches: sizes, shared, similarity. Mergeable, of fixed size."""
    x = a.agg(F.expr(f"theta_sketch_agg(h, {lg})").alias("x")).crossJoin(b.agg(F.expr(f"theta_sketch_agg(h, {lg})").alias("y")))
    sizes = x.selectExpr("theta_sketch_estimate(x) as card_a", "theta_sketch_estimate(y) as card_b", "theta_sketch_estimate(theta_intersection(x, y)) as shared", "theta_sketch_estimate(theta_union(x, y)) as either")
    return sizes.withColumn("similarity", F.col("shared") / F.greatest(F.col("either"), F.lit(1)))


def strata(a: DataFrame, b: DataFrame, levels: int = 20) -> DataFrame:
    """One row: an estimate of the symmetric difference by halving samples.

    A digest is of the level that its trailing zero bits give. Level by level from the sparsest, the exact difference
    of samples is counted, until a level has many; it is scaled by that level's share.
    """
    zeros = lambda x: x.select("h", F.least(F.bit_count(F.col("d2").bitwiseXOR(F.col("d2") - 1)) - 1, F.lit(levels)).cast("int").alias("level"))
    apart = zeros(a).withColumn("x", F.lit(1)).unionByName(zeros(b).withColumn("x", F.lit(2))).groupBy("h", "level").agg(F.bit_or("x").alias("x")).where("x < 3")
    per_level = apart.groupBy("level").agg(F.count("*").alias("n"))
    numbers = per_level.agg(F.sort_array(F.collect_list(F.struct((-F.col("level")).alias("down"), "n"))).alias("rows"))  # levels + 1 rows at most
    running = F.aggregate("rows", F.struct(F.lit(0).cast("bigint").alias("n"), F.lit(levels + 1).alias("level")), lambda s, r: F.when(s["n"] >= 64, s).otherwise(F.struct((s["n"] + r["n"]).alias("n"), (-r["down"]).alias("level"))))
    return numbers.select(F.coalesce(running["n"] * F.pow(F.lit(2.0), running["level"]), F.lit(0.0)).alias("difference"))


def estimate_difference(a: DataFrame, b: DataFrame, how: str = "bottom_k") -> DataFrame:
    """One row with similarity (bottom_k, theta) or difference (strata)."""
    return {"bottom_k": bottom_k, "theta": theta, "strata": strata}[how](a, b)
