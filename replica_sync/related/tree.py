"""Hash trees: level by level only the children of mismatched nodes are compared."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from replica_sync.sources.tables import snapshot


def nodes(parts: DataFrame, depth: int) -> DataFrame:
    """prefix, x, y, n: order-free digests of the parts below each node of one level (16 children a node)."""
    return parts.groupBy(F.substring("h", 1, depth).alias("prefix")).agg(F.bit_xor("d").alias("x"), F.bit_xor("d2").alias("y"), F.count("*").alias("n"))


def level_mismatch(a: DataFrame, b: DataFrame, depth: int, above: DataFrame | None = None) -> DataFrame:
    """prefix, compared on one level: nodes that differ, below the mismatched nodes of the level above."""
    if above is not None:
        keep = above.select(F.col("prefix").alias("up"))
        a, b = (p.join(keep, F.substring("h", 1, depth - 1) == F.col("up"), "left_semi") for p in (a, b))
    x, y = nodes(a, depth), nodes(b, depth)
    both = x.alias("l").join(y.alias("r"), "prefix", "full_outer")
    same = F.col("l.x").eqNullSafe(F.col("r.x")) & F.col("l.y").eqNullSafe(F.col("r.y")) & F.col("l.n").eqNullSafe(F.col("r.n"))
    return both.select("prefix", (~same).alias("differs"))


def tree_sync(a: DataFrame, b: DataFrame, depth: int = 3) -> tuple[DataFrame, DataFrame]:
    """(level, compared, differing) and the mismatched leaves' prefixes."""
    above, rows = None, None
    for level in range(1, depth + 1):
        found = snapshot(level_mismatch(a, b, level, above), "tree-level")
        row = found.agg(F.lit(level).alias("level"), F.count("*").alias("compared"), F.count_if("differs").alias("differing"))
        rows = row if rows is None else rows.unionByName(row)
        above = found.where("differs").select("prefix")
    return rows, above
