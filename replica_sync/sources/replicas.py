"""Pairs of replicas: of a set similarity, natural splits, strings of uniform lengths."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from replica_sync.functions.digest import with_digest
from replica_sync.sources import tables


def shared_count(s: float, c: int) -> int:
    """Items in both of two sets of c items each whose Jaccard similarity is s."""
    return round(2 * s * c / (1 + s))


def ranked(parts: DataFrame) -> DataFrame:
    """rank (from 1) and size over all parts by digest, without ordering them in one task.

    The digest's first three hex digits cut the order into ranges; a row's rank is its place in its
    range plus what the ranges before hold (4,096 sums).
    """
    cut = F.substring("h", 1, 3)
    ranges = parts.groupBy(cut.alias("range")).count()
    before = Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    sums = ranges.select("range", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("before"), F.sum("count").over(Window.partitionBy()).alias("size"))
    placed = parts.withColumn("range", cut).withColumn("place", F.row_number().over(Window.partitionBy("range").orderBy("h")))
    return placed.join(F.broadcast(sums), "range").withColumn("rank", F.col("place") + F.col("before")).drop("range", "place", "before")  # at most 4,096 rows


def make_pair(parts: DataFrame, s: float, c: int | None = None, mode: str = "exact") -> DataFrame:
    """Adds side ('both', 'a', 'b'); parts of neither side go.

    exact: c items a side (by default half of all) with the shared count rounded; threshold: no exchange,
    similarity s up to sampling error.
    """
    if mode == "threshold":
        low = F.col("d") / F.lit(float(1 << 60))
        return parts.withColumn("side", F.when(low < s, "both").when(F.col("d2") % 2 == 0, "a").otherwise("b"))
    return sided(ranked(parts), F.lit(float(s)), c).drop("rank", "size")


def sided(rows: DataFrame, s: Column, c: int | None = None) -> DataFrame:
    """Of ranked parts those of a pair of similarity s (a Column: several pairs at once)."""
    each = F.lit(c) if c is not None else F.floor(F.col("size") / 2)
    shared = F.round(2 * s * each / (1 + s)).cast("bigint")
    side = F.when(F.col("rank") <= shared, "both").when(F.col("rank") <= each, "a").when(F.col("rank") <= 2 * each - shared, "b")
    return rows.withColumn("side", side).where(F.col("side").isNotNull())


def sides(pair: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The two replicas of a pair, apart from each other."""
    return pair.where(F.col("side").isin("both", "a")).drop("side"), pair.where(F.col("side").isin("both", "b")).drop("side")


def jaccard(a: DataFrame, b: DataFrame, key: str = "h") -> DataFrame:
    """One row: shared, either, similarity (1 for two empty sides). One exchange."""
    both = a.select(key, F.lit(1).alias("x")).unionAll(b.select(key, F.lit(2).alias("x"))).groupBy(key).agg(F.bit_or("x").alias("x"))
    return both.agg(F.count_if(F.col("x") == 3).alias("shared"), F.count("*").alias("either")).withColumn("similarity", F.coalesce(F.try_divide("shared", "either"), F.lit(1.0)))


def uniform_strings(items: DataFrame, lo: int, hi: int) -> DataFrame:
    """payload: strings of lengths spread evenly over lo to hi, headed by the item's digest; distinct from a least length of 32 on."""
    more = ", ".join(f"sha2(cast(concat(payload, '{'+' * k}') as binary), 256)" for k in range(max(2, -(-(hi - 32) // 64))))
    spread = f"substr(concat(h, {more}), 1, cast({lo} + d % ({hi} - {lo} + 1) as int))"
    return with_digest(items.select("payload")).select(F.expr(spread).alias("payload"))


def natural_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two replicas that saw the events before one day and from an earlier day on. One scan."""
    ts = F.col("ts").cast("timestamp_ntz")
    in_a, in_b = ts < F.expr("timestamp_ntz'2024-01-21 00:00:00'"), ts >= F.expr("timestamp_ntz'2024-01-11 00:00:00'")
    side = F.when(in_a & in_b, "both").when(in_a, "a").when(in_b, "b")
    return with_digest(tables.load_items(spark, sf_dir, "events", side=side).where("side is not null").select("payload", "nbytes", "side"))


def natural_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Texts of even-numbered sources against those of odd-numbered ones; copies fall on both sides."""
    rows = tables.read(spark, sf_dir, "documents").select(F.col("text").alias("payload"), (F.regexp_extract("source", r"(\d+)$", 1).cast("int") % 2).alias("odd"))
    side = F.when(F.min("odd") != F.max("odd"), "both").when(F.min("odd") == 0, "a").otherwise("b")
    return with_digest(rows.groupBy("payload").agg(side.alias("side"))).withColumn("nbytes", F.octet_length("payload"))
