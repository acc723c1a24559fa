"""Connected components of a table of links, without collecting it."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from replica_sync.llm.common import dropped, kept_as_table


def _both_ways(links: DataFrame) -> DataFrame:
    turned = links.select(F.col("b").alias("a"), F.col("a").alias("b"))
    return links.select("a", "b").unionByName(turned).where(F.col("a") != F.col("b"))


def nearer(links: DataFrame, roots: DataFrame | None = None) -> DataFrame:
    """One step from roots (node, root; each node its own where there is none) towards the components of links (a, b).

    Every node takes the least root around it, what was below its old root follows, and then each root's own root is
    taken: roots only fall, and a root is always reached by links.
    """
    both = _both_ways(links)
    if roots is None:
        start = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("root")).withColumnRenamed("a", "node").withColumn("old", F.col("node"))
    else:
        known = both.join(roots.withColumnRenamed("node", "b"), "b", "left").withColumn("root", F.coalesce("root", "b"))
        near = known.groupBy("a").agg(F.min("root").alias("near")).withColumnRenamed("a", "node")
        start = near.join(roots.withColumnRenamed("root", "old"), "node", "left").withColumn("old", F.coalesce("old", "node")).withColumn("root", F.least("near", "old")).drop("near")
    hooked = start.select(F.col("old").alias("node"), "root").unionByName(start.select("node", "root")).groupBy("node").agg(F.min("root").alias("root"))
    hooked = kept_as_table(hooked, "hooked")
    above = hooked.select(F.col("node").alias("root"), F.col("root").alias("above"))
    out = kept_as_table(hooked.join(above, "root", "left").select("node", F.coalesce("above", "root").alias("root")), "roots")
    dropped(hooked)
    return out


def components(links: DataFrame, roots: DataFrame | None = None, most_rounds: int = 80) -> DataFrame:
    """links (a, b) to (node, root): root is the smallest node of each component.

    roots: (node, root) of an earlier step, if there is one. Rounds grow with the logarithm of a component's width; hot nodes are
    reduced by partial aggregates. An empty table gives an empty result.
    """
    roots = nearer(links, roots)
    for _ in range(most_rounds):
        stepped = nearer(links, roots)
        moved = not stepped.join(roots.withColumnRenamed("root", "old"), "node").where("root != old").isEmpty()
        dropped(roots)
        roots = stepped
        if not moved:
            return roots
    raise RuntimeError(f"components did not settle in {most_rounds} rounds")
