"""The given tables as canonical item strings, and tables in the shared folder."""

from __future__ import annotations

import gc
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.storagelevel import StorageLevel

from replica_sync.functions.digest import with_digest

#: Key column and the parts of the item string of each table, in file order: text as is, c: cents, d: date, u: microseconds.
ITEMS = {
    "region": ("r_regionkey", "r_regionkey r_name"),
    "nation": ("n_nationkey", "n_nationkey n_name n_regionkey"),
    "customer": ("c_custkey", "c_custkey c_name c_nationkey c:c_acctbal c_mktsegment"),
    "supplier": ("s_suppkey", "s_suppkey s_name s_nationkey c:s_acctbal"),
    "part": ("p_partkey", "p_partkey p_name p_brand p_type p_size c:p_retailprice"),
    "orders": ("o_orderkey", "o_orderkey o_custkey o_orderstatus c:o_totalprice d:o_orderdate o_orderpriority"),
    "lineitem": ("l_orderkey", "l_orderkey l_partkey l_suppkey l_linenumber c:l_quantity c:l_extendedprice c:l_discount c:l_tax l_returnflag l_linestatus d:l_shipdate"),
    "events": ("event_id", "event_id user_id event_type c:value props u:ts"),
    "documents": ("doc_id", "text"),
    "benchmark": ("item_id", "text"),
    "pages": ("page_id", "url html"),
    "conversations": ("conv_id", "conv_id turn role text"),
}
EPOCH = "timestamp_ntz'1970-01-01 00:00:00'"


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def _piece(spec: str) -> Column:
    kind, _, name = spec.rpartition(":")
    if kind == "c":
        return F.round(F.col(name) * 100).cast("bigint").cast("string")
    if kind == "d":
        return F.date_format(name, "yyyy-MM-dd")
    if kind == "u":
        return F.expr(f"timestampdiff(MICROSECOND, {EPOCH}, cast({name} as timestamp_ntz))").cast("string")
    return F.col(name).cast("string")


def _piece_sql(spec: str) -> str:
    kind, _, name = spec.rpartition(":")
    return {"c": f"cast(cast(round({name}*100) as bigint) as varchar)", "d": f"strftime({name}, '%Y-%m-%d')", "u": f"cast(epoch_us({name}) as varchar)"}.get(kind, f"cast({name} as varchar)")


def load_items(spark: SparkSession, sf_dir: str, table: str, **more: Column) -> DataFrame:
    """part_key, payload, nbytes, and more columns if named: one canonical string per row. Narrow; only the named columns are read."""
    key, pieces = ITEMS[table]
    payload = F.concat_ws("|", *map(_piece, pieces.split()))
    return read(spark, sf_dir, table).select(F.col(key).cast("string").alias("part_key"), payload.alias("payload"), *[c.alias(n) for n, c in more.items()]).withColumn("nbytes", F.octet_length("payload"))


def items_sql(table: str) -> str:
    """The same in the oracle's SQL."""
    key, pieces = ITEMS[table]
    return f"select cast({key} as varchar) as part_key, concat_ws('|', {', '.join(map(_piece_sql, pieces.split()))}) as payload from {table}"


def digests_sql(source: str) -> str:
    """payload to payload, nbytes, h, d, d2."""
    return f"select payload, octet_length(encode(payload)) as nbytes, md5(payload) as h, ('0x'||substr(md5(payload),1,15))::bigint as d, ('0x'||substr(md5(payload),17,15))::bigint as d2 from ({source})"


def parts_of(spark: SparkSession, sf_dir: str, table: str, segments: int = 1) -> DataFrame:
    """The table's items as a set of parts."""
    return with_digest(load_items(spark, sf_dir, table).select("payload", "nbytes").distinct(), segments=segments)


_scopes: list[str] = []  # folders of open passing() blocks, the innermost last


def dropped(spark: SparkSession, folder: str) -> None:
    """Deletes a folder of this session's own that nothing reads any more, and lets the session's cleaner find exchange files that nothing refers to."""
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
    gc.collect()
    spark._jvm.System.gc()


@contextmanager
def passing(spark: SparkSession) -> Iterator[None]:
    """What is written below the shared folder inside goes when the block ends: results have to be kept by paths from outside."""
    folder = shared_folder(spark, "passing")
    _scopes.append(folder)
    try:
        yield
    finally:
        _scopes.remove(folder)
        dropped(spark, folder)


#: Rows of a place: what a task joins and groups in memory at a time.
PLACE_ROWS = 100_000
#: Joins use the places that their rows lie in, and rows that lie in the order of their groups are not hashed.
BY_PLACE = {"spark.sql.requireAllClusterKeysForCoPartition": "false", "spark.sql.execution.useObjectHashAggregateExec": "false"}
_places: list[tuple[int, list[DataFrame]]] = []  # places and kept frames of open placing() blocks, the innermost last


@contextmanager
def placing(spark: SparkSession, rows: int) -> Iterator[None]:
    """Inside, placed() keeps frames of about so many rows by their keys, until the block ends: results have to be written before."""
    before = {name: spark.conf.get(name) for name in BY_PLACE}
    held: list[DataFrame] = []
    _places.append((max(2, -(-rows // PLACE_ROWS)), held))
    for name, value in BY_PLACE.items():
        spark.conf.set(name, value)
    try:
        yield
    finally:
        _places.pop()
        for name, value in before.items():
            spark.conf.set(name, value)
        for df in held:
            df.unpersist()


def placed(df: DataFrame, keys: list[str], name: str = "", order: list[str] = ()) -> DataFrame:
    """Rows kept on the executors' disks, those of equal keys in one place, there in the order given: joins and groups by the keys, and more,
    do not exchange them again. They are made again from df where an executor is lost. Outside of placing() they are a snapshot of that
    name, or df as it is.
    """
    if not _places:
        return snapshot(df, name) if name else df
    places, held = _places[-1]
    kept = df.repartition(places, *keys)
    kept = (kept.sortWithinPartitions(*order) if order else kept).persist(StorageLevel.DISK_ONLY)
    held.append(kept)
    return kept


def hashed(df: DataFrame) -> DataFrame:
    """A side of a join by places, as a table in memory of one place at a time: no sorting. Outside of placing() the planner decides."""
    return df.hint("shuffle_hash") if _places else df


def shared_folder(spark: SparkSession, name: str) -> str:
    """A new folder below spark.checkpoint.dir, or the context's checkpoint folder; a temporary one only in local mode, where all share one machine."""
    base = _scopes[-1] if _scopes else spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        kept = spark.sparkContext._jsc.sc().getCheckpointDir()
        base = kept.get() if kept.isDefined() else None
    if not base and spark.sparkContext.master.startswith("local["):
        base = "file://" + tempfile.mkdtemp(prefix="replica_sync_")
        spark.sparkContext.setCheckpointDir(base)
    if not base:
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def snapshot(df: DataFrame, name: str = "snapshot", path: str | None = None) -> DataFrame:
    """An immutable copy in Parquet, read again: ends the lineage, survives lost executors."""
    path = path or shared_folder(df.sparkSession, name)
    df.write.mode("overwrite").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


class MessageDirectory:
    """A reliable ordered channel: one Parquet folder per message, read again in order after a broken session."""

    def __init__(self, spark: SparkSession, path: str | None = None):
        self.spark, self.path, self.sent = spark, path or shared_folder(spark, "messages"), 0

    def send(self, kind: str, rows: DataFrame) -> DataFrame:
        self.sent += 1
        return snapshot(rows, path=f"{self.path}/{self.sent:06d}-{kind}")

    def receive(self, seq: int, kind: str) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/{seq:06d}-{kind}")


def event_stream(spark: SparkSession, sf_dir: str, files_at_once: int | None = None) -> DataFrame:
    """The events table as a stream of its file, timestamps made fit for watermarks."""
    schema = read(spark, sf_dir, "events").schema
    reader = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet")
    if files_at_once:
        reader = reader.option("maxFilesPerTrigger", files_at_once)
    return reader.parquet(sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))


def export(df: DataFrame, path: str, fmt: str = "parquet") -> DataFrame:
    """Writes and reads again in Parquet, ORC, JSON or CSV; text formats get the schema back by name."""
    df.write.mode("overwrite").format(fmt).option("header", "true").save(path)
    reader = df.sparkSession.read.format(fmt).schema(df.schema)
    return (reader.option("header", "true") if fmt == "csv" else reader).load(path).select(*df.columns)
