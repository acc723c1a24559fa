"""SQL names of the building blocks: part_digest, bucket_of, filter_position, coded_cells, decompose_json."""

from __future__ import annotations

import json

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from replica_sync.operators.coded import walk


@udtf(returnType="i int")
class CodedCells:
    """Indices of the cells that hold a digest, from lo to below hi."""

    def eval(self, d: int, lo: int, hi: int):
        for i in walk(d, hi):
            if i >= lo:
                yield (i,)


@udtf(returnType="key string, value string")
class DecomposeJson:
    """The entries of a JSON object: one part per key."""

    def eval(self, text: str):
        for key, value in sorted((json.loads(text) if text else {}).items()):
            yield key, json.dumps(value)


def register(spark: SparkSession) -> None:
    """Temporary functions of this session; those in plain SQL are inlined into the plans that use them."""
    spark.sql("create or replace temporary function part_digest(payload string) returns bigint return cast(conv(substring(md5(cast(payload as binary)), 1, 15), 16, 10) as bigint)")
    spark.sql("create or replace temporary function bucket_of(payload string, n bigint) returns bigint return cast(conv(substring(md5(cast(payload as binary)), 1, 15), 16, 10) as bigint) % n")
    spark.sql("create or replace temporary function filter_position(d bigint, d2 bigint, i bigint, m bigint) returns bigint return (d % m + i * (d2 % m)) % m")
    spark.udtf.register("coded_cells", CodedCells)
    spark.udtf.register("decompose_json", DecomposeJson)
