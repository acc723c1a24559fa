"""Mixing sources to target weights: capped water-filling, then seeded whole and fractional repetitions. DataFrame only.

Targets: t_s = min(cap_s, level * weight_s), where cap_s is max_epochs times the source's size and the
level makes all targets add up to the whole. With the sources sorted by cap/weight, the sources below
the breakpoint stop at their cap and the rest share what is left by weight: running sums give it.

Takes: each document is taken floor(t_s / size_s) whole times; one more repetition goes to the
documents first in a seeded order, until the source's fractional part is filled. The document in which it
runs out is taken as a fraction: up to that word. The order is cut into ranges, and only the range
with that document is sorted, so that no source, however large, is ordered in one task.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from replica_sync.llm.common import WORD, kept_as_table, pick

#: The weights that sources get by turns.
WEIGHTS = (5, 2, 1)
RANGES = 1024


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def sources_of(sized: DataFrame, weights: tuple[int, ...] = WEIGHTS) -> DataFrame:
    """source, source_size, weight: one row per source, weights by turns in code-point order, null last."""
    turn = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    weight = F.element_at(F.array(*map(F.lit, weights)), (turn % len(weights) + 1).cast("int"))
    return sized.groupBy("source").agg(F.sum("size").alias("source_size")).withColumn("weight", weight.cast("long"))


def water_filled(sources: DataFrame, max_epochs: int = 3) -> DataFrame:
    """Adds target: the capped shares of the whole. Sources without words get 0."""
    cap = F.col("source_size") * max_epochs
    by_ratio = Window.orderBy((cap / F.col("weight")).asc(), "weight", F.col("source").asc_nulls_last())
    before = by_ratio.rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.partitionBy()
    left = F.sum("source_size").over(everything) - F.coalesce(F.sum(cap).over(before), F.lit(0))
    weights_left = F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(before), F.lit(0))
    level = left / weights_left  # the level if this source is the first that is not capped
    free = level * F.col("weight") <= cap
    found = F.min(F.when(F.col("free"), F.struct("place", "level"))).over(everything)["level"]
    ranked = sources.withColumn("level", level).withColumn("free", free).withColumn("place", F.row_number().over(by_ratio))
    return ranked.withColumn("target", F.least(cap.cast("double"), F.coalesce(found * F.col("weight"), cap.cast("double")))).drop("level", "free", "place")


def _keyed(rows: DataFrame, seed: int) -> DataFrame:
    """Adds size and key, the document's place in the seeded order."""
    name = F.concat_ws("#", F.lit(str(seed)), F.coalesce(F.col("doc_id").cast("string"), F.lit("null")))
    return rows.withColumn("size", word_count(F.col("text"))).withColumn("key", F.conv(F.substring(F.md5(name.cast("binary")), 1, 12), 16, 10).cast("long"))


def _piece(ranges: int) -> Column:
    return F.floor(F.col("key") / F.lit(2**48 // ranges)).cast("int")


def mixing_plan(sized: DataFrame, weights: tuple[int, ...] = WEIGHTS, max_epochs: int = 3, ranges: int = RANGES) -> DataFrame:
    """One row per source: of, source_size, target, whole repetitions, part (words of one more), cut (the range in which part
    runs out) and ahead (words in the ranges before it). sized: source, size, key."""
    per_range = kept_as_table(sized.groupBy("source", _piece(ranges).alias("piece")).agg(F.sum("size").alias("held")), "mix-ranges")
    mixed = water_filled(sources_of(per_range.withColumnRenamed("held", "size"), weights), max_epochs)
    ratio = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    shares = kept_as_table(mixed.select(F.col("source").alias("of"), "source_size", "target", F.floor(ratio).alias("whole"), (F.col("target") - F.floor(ratio) * F.col("source_size")).alias("part")), "mix-shares")
    so_far = Window.partitionBy("source").orderBy("piece").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    upto = per_range.withColumn("upto", F.sum("held").over(so_far)).join(shares.select("of", "part"), F.col("source").eqNullSafe(F.col("of")))
    last = upto.groupBy("of").agg(F.min(F.when(F.col("upto") > F.col("part"), F.col("piece"))).alias("cut"), F.max(F.when(F.col("upto") <= F.col("part"), F.col("upto"))).alias("ahead"))
    own = shares.withColumnRenamed("of", "source").join(last, F.col("source").eqNullSafe(F.col("of")))
    return kept_as_table(own.select(F.col("source").alias("of"), "source_size", "target", "whole", "part", F.coalesce("cut", F.lit(ranges)).alias("cut"), F.coalesce("ahead", F.lit(0)).alias("ahead")), "mix-plan")


def _mixed(sized: DataFrame, plan: DataFrame, max_epochs: int, ranges: int) -> DataFrame:
    """Adds the plan's columns, taken and repeats. Only the range in which a source's part runs out is put in order."""
    found = sized.withColumn("piece", _piece(ranges)).join(plan, F.col("source").eqNullSafe(F.col("of")))
    here = F.col("piece") == F.col("cut")
    beside = found.where(~here).withColumn("more", F.when(F.col("piece") < F.col("cut"), F.col("size")).otherwise(F.lit(0)).cast("long"))
    in_order = Window.partitionBy("source").orderBy("key", F.col("doc_id").asc_nulls_first(), "size").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    before = F.col("ahead") + F.sum("size").over(in_order) - F.col("size")
    within = found.where(here).withColumn("more", F.greatest(F.lit(0), F.least(F.col("size"), F.round(F.col("part")).cast("long") - before)).cast("long"))
    both = beside.unionByName(within)
    taken = F.least(F.col("whole").cast("long") * F.col("size") + F.col("more"), max_epochs * F.col("size"))
    return both.withColumn("taken", taken).withColumn("repeats", F.when(F.col("size") > 0, F.col("taken") / F.col("size")).otherwise(F.lit(0.0)))


def mix_sources(docs: DataFrame, doc_id: str = "doc_id", source: str = "source", text: str = "text", weights: tuple[int, ...] = WEIGHTS, max_epochs: int = 3, seed: int = 17, ranges: int = RANGES) -> DataFrame:
    """doc_id, size, source_size, target, repeats, taken for every row.

    size counts words (null text: 0); the seeded order is by md5 of seed and doc_id, ties by doc_id and size, so
    reruns agree. taken = repeats * size and repeats <= max_epochs; repeats is whole but for one document of a
    source. Null sources form one source of their own; a source without words has target 0 and takes
    nothing. An empty table gives an empty result; other columns are not read.
    """
    rows = pick(docs, doc_id=doc_id, source=source, text=text)
    sized = kept_as_table(_keyed(rows, seed).drop("text"), "mix-sizes")
    return _mixed(sized, mixing_plan(sized, weights, max_epochs, ranges), max_epochs, ranges).select("doc_id", "size", "source_size", "target", "repeats", "taken")


def repeated_rows(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, max_epochs: int = 3, seed: int = 17, ranges: int = RANGES) -> DataFrame:
    """The rows of docs (doc_id, source, text and others), each as often as the mix takes it.

    The one document in which a source's part runs out is taken once more if at least half of it is due, so texts stay
    whole; texts without words are not taken.
    """
    names = docs.columns
    packed = docs.select("doc_id", "source", "text", F.struct(*[F.col(f"`{c}`") for c in names]).alias("row"))
    sized = _keyed(packed, seed).drop("text")
    plan = mixing_plan(_keyed(pick(docs, doc_id="doc_id", source="source", text="text"), seed).drop("text"), weights, max_epochs, ranges)
    copies = F.explode(F.sequence(F.lit(1), F.round("repeats").cast("int"))).alias("copy")
    return _mixed(sized, plan, max_epochs, ranges).where(F.round("repeats") >= 1).select("row", copies).select("row.*")
