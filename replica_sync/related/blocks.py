"""Files as blocks: which parts of the primary's file the secondary already has, by weak and strong signatures.

Files are rows (id, text). The secondary's blocks have fixed places; the primary's windows start anywhere.
Characters are compared as code points; weak signatures are sums, strong ones md5.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def weak_signature(text: Column) -> Column:
    """A sum of code points and a sum of its running sums: cheap, and computable from the one before."""
    codes = F.transform(F.filter(F.split(text, ""), lambda c: c != ""), lambda c: F.ascii(c))
    state = F.struct(F.lit(0).cast("bigint").alias("s"), F.lit(0).cast("bigint").alias("r"))
    return F.aggregate(codes, state, lambda a, c: F.struct((a["s"] + c).alias("s"), (a["r"] + a["s"] + c).alias("r")), lambda a: a["s"] % 65521 + (a["r"] % 65521) * 65536)


def blocks(files: DataFrame, block: int) -> DataFrame:
    """id, off, strong, weak, data of the whole blocks at fixed offsets."""
    at = F.explode(F.expr(f"sequence(0, cast(greatest(char_length(text) - 1, 0) as int), {block})")).alias("off")
    cut = files.where(F.length("text") > 0).select("id", "text", at).select("id", "off", F.expr(f"substring(text, off + 1, {block})").alias("data"))
    return cut.withColumn("strong", F.md5(F.col("data").cast("binary"))).withColumn("weak", weak_signature(F.col("data")))


def fixed_block_diff(primary: DataFrame, secondary: DataFrame, block: int) -> DataFrame:
    """id, blocks, literal_chars: only blocks equal at the same place are saved, so that one inserted character spoils all."""
    p, s = blocks(primary, block), blocks(secondary, block).select("id", "off", F.col("strong").alias("have"))
    both = p.join(s, ["id", "off"], "left")
    return both.groupBy("id").agg(F.count("*").alias("blocks"), F.sum(F.when(F.col("strong").eqNullSafe(F.col("have")), 0).otherwise(F.length("data"))).cast("bigint").alias("literal_chars"))


def windows(files: DataFrame, block: int) -> DataFrame:
    """id, off, data of windows of block characters at every offset."""
    last = F.expr(f"sequence(0, cast(char_length(text) - {block} as int))")
    return files.where(F.length("text") >= block).select("id", "text", F.explode(last).alias("off")).select("id", "off", F.expr(f"substring(text, off + 1, {block})").alias("data"))


def every_offset_diff(primary: DataFrame, secondary: DataFrame, block: int) -> DataFrame:
    """id, off, from_off: windows at any offset whose strong signature is one of the secondary's blocks. Costs a strong digest per offset."""
    have = blocks(secondary, block).where(F.length("data") == block).groupBy("id", "strong").agg(F.min("off").alias("from_off"))
    return windows(primary, block).withColumn("strong", F.md5(F.col("data").cast("binary"))).join(have, ["id", "strong"]).select("id", "off", "from_off")


def block_sync(primary: DataFrame, secondary: DataFrame, block: int) -> DataFrame:
    """id, copied, literal_chars, strong_checks: the script that rebuilds the primary's file at the secondary.

    Windows pass the weak signature before a strong one is computed; matches are then taken from left to right
    without overlap.
    """
    have = blocks(secondary, block).where(F.length("data") == block)
    weak = have.select("id", "weak").distinct()
    passed = windows(primary, block).withColumn("weak", weak_signature(F.col("data"))).join(weak, ["id", "weak"], "left_semi")
    strong = have.groupBy("id", "strong").agg(F.min("off").alias("from_off"))
    checked = passed.withColumn("strong", F.md5(F.col("data").cast("binary")))
    matched = checked.join(strong, ["id", "strong"]).groupBy("id").agg(F.sort_array(F.collect_list("off")).alias("offs"))
    state = F.struct(F.lit(0).alias("free"), F.lit(0).alias("n"))
    taken = F.aggregate("offs", state, lambda a, o: F.when(o >= a["free"], F.struct((o + block).alias("free"), (a["n"] + 1).alias("n"))).otherwise(a), lambda a: a["n"])
    checks = checked.groupBy("id").agg(F.count("*").alias("strong_checks"))
    out = primary.select("id", F.length("text").alias("chars")).join(matched.select("id", taken.alias("copied")), "id", "left").join(checks, "id", "left")
    copied = F.coalesce("copied", F.lit(0))
    return out.select("id", copied.cast("bigint").alias("copied"), (F.col("chars") - copied * block).cast("bigint").alias("literal_chars"), F.coalesce("strong_checks", F.lit(0)).cast("bigint").alias("strong_checks"))
