"""Hash buckets of parts and their digests. All functions work on many sessions (sid) at once."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from replica_sync.sources.tables import hashed


def bucket_count(n: Column | int | float, load_factor: Column | float):
    """Buckets for n parts: the floor of n times the load factor, at least 1."""
    if isinstance(n, Column) or isinstance(load_factor, Column):
        product = (n if isinstance(n, Column) else F.lit(n)) * (load_factor if isinstance(load_factor, Column) else F.lit(load_factor))
        return F.greatest(F.floor(product), F.lit(1))
    return max(1, int(n * load_factor))


def with_bucket(parts: DataFrame, n_buckets: Column | int) -> DataFrame:
    n = n_buckets if isinstance(n_buckets, Column) else F.lit(n_buckets)
    return parts.withColumn("bucket", F.pmod(F.col("d"), n).cast("bigint"))


def bucket_digests(bucketed: DataFrame, how: str = "ordered") -> DataFrame:
    """sid, bucket, n_parts, nbytes, digest of every non-empty bucket.

    ordered: md5 of the members' digests in order, seeded with the bucket's index. xor: an order-free digest from
    partial aggregates alone, for buckets too large for one task.
    """
    if how == "ordered":
        digest = F.md5(F.concat(F.col("bucket").cast("string"), F.lit(":"), F.array_join(F.sort_array(F.collect_list("h")), "")).cast("binary"))
    else:
        digest = F.md5(F.concat_ws(":", F.col("bucket").cast("string"), F.bit_xor("d").cast("string"), F.bit_xor("d2").cast("string"), F.count("*").cast("string")).cast("binary"))
    grouped = bucketed.groupBy("bucket", "sid").agg(F.count("*").alias("n_parts"), F.sum("nbytes").alias("nbytes"), digest.alias("digest"))
    return grouped.select("sid", "bucket", "n_parts", "nbytes", "digest")


def mismatched(ours: DataFrame, theirs: DataFrame) -> DataFrame:
    """sid, bucket of buckets whose digests differ or that one side lacks."""
    a, b = ours.select("sid", "bucket", F.col("digest").alias("x")), theirs.select("sid", "bucket", F.col("digest").alias("y"))
    return a.join(hashed(b), ["sid", "bucket"], "full_outer").where(~F.col("x").eqNullSafe(F.col("y"))).select("sid", "bucket")


def all_bucket_digests(digests: DataFrame, counts: DataFrame) -> DataFrame:
    """Adds the empty buckets: counts has sid, n_buckets. Every bucket then has one digest on each side."""
    every = counts.select("sid", F.explode(F.sequence(F.lit(0), F.col("n_buckets") - 1)).alias("bucket"))
    empty = F.md5(F.concat(F.col("bucket").cast("string"), F.lit(":")).cast("binary"))
    return every.join(digests.select("sid", "bucket", "digest"), ["sid", "bucket"], "left").withColumn("digest", F.coalesce("digest", empty))
