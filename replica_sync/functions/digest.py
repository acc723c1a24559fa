"""Digests of parts: md5 in hex, its first 60 bits as a number, 60 more for double hashing, and a segment."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def hex_number(hex_text: Column, first: int, n: int) -> Column:
    """n hex digits from a place on, as a number that is never negative (n at most 15)."""
    return F.conv(F.substring(hex_text, first, n), 16, 10).cast("bigint")


def digest_text(payload: Column, family: str = "md5") -> Column:
    """Hex digest; every family yields at least 32 digits."""
    if family == "md5":
        return F.md5(payload.cast("binary"))
    if family == "sha2":
        return F.sha2(payload.cast("binary"), 256)
    if family == "xxhash64":
        return F.concat(*[F.lpad(F.lower(F.hex(F.xxhash64(payload, F.lit(k)))), 16, "0") for k in (0, 1)])
    raise ValueError(f"no digest family {family}")


def segment_of(segments: int) -> Column:
    """Segment of a part: middle bits of d2, so that it tells nothing about the remainders that filters and buckets take."""
    return (F.shiftright("d2", 30) % segments).cast("int")


def with_digest(df: DataFrame, family: str = "md5", segments: int = 1) -> DataFrame:
    """Adds h, d, d2 and seg to rows with a payload: narrow, inside generated code for the built-in families."""
    hashed = df.withColumn("h", digest_text(F.col("payload"), family))
    numbers = hashed.withColumn("d", hex_number(F.col("h"), 1, 15)).withColumn("d2", hex_number(F.col("h"), 17, 15))
    return numbers.withColumn("seg", segment_of(segments))
