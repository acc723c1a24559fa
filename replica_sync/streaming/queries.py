"""Synchronisation over streams: periodic anti-entropy, decoding of cell streams, lattice states, windowed volumes.

Every query drains its source with the availableNow trigger into a table of the shared folder or memory.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from replica_sync.functions.digest import with_digest
from replica_sync.functions.wire import SyncConfig
from replica_sync.operators import coded
from replica_sync.operators.lattice import KeyedLattice
from replica_sync.protocols import PROTOCOLS, Replicas
from replica_sync.sources.tables import digests_sql, event_stream, items_sql, load_items, parts_of, read, shared_folder, snapshot

QUERIES: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str | None]] = {}


def query(sql: str | None):
    def register(f: Callable[[SparkSession, str], DataFrame]):
        QUERIES[f.__name__] = (f, sql)
        return f

    return register


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream until its input is used up; the result as a table of the shared folder, the last one in complete mode."""
    spark, base = stream.sparkSession, shared_folder(stream.sparkSession, "stream")
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{base}/checkpoint").trigger(availableNow=True)
    path, last = f"{base}/rows", []

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/{number}")
        last[:] = [f"{path}/{number}"]

    running = writer.format("parquet").option("path", path).start() if mode == "append" else writer.foreachBatch(keep).start()
    running.awaitTermination()
    if mode != "append" and not last:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(path if mode == "append" else last[0])


def files_of(df: DataFrame, order: str, files: int, again: int = 0, latest: bool = False) -> str:
    """A folder with df as several files in order, the first (or latest) rows perhaps once more at the end: replayed input."""
    path = shared_folder(df.sparkSession, "event-files")
    pieces = snapshot(df.repartitionByRange(files, order).withColumn("piece", F.spark_partition_id()), "pieces")
    for k in range(files):  # one after the other: a stream reads files by age
        pieces.where(F.col("piece") == k).drop("piece").coalesce(1).sortWithinPartitions(order).write.parquet(f"{path}/a/{k}")
    if again:
        df.orderBy(F.desc(order) if latest else order).limit(again).coalesce(1).write.parquet(f"{path}/b")
    return path


def stream_of(spark: SparkSession, path: str, schema) -> DataFrame:
    return spark.readStream.schema(schema).option("recursiveFileLookup", "true").option("maxFilesPerTrigger", 1).parquet(path)


def replayed(spark: SparkSession, sf: str, latest: bool = False) -> DataFrame:
    """Events as a stream of six files, some events twice."""
    e = read(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return stream_of(spark, files_of(e, "ts", 6, 100, latest), e.schema)


def stream_state(stream: DataFrame, lattice: KeyedLattice) -> DataFrame:
    """The lattice state of a log as it grows: the join is an aggregate in update or complete mode."""
    return lattice.compose(stream)


def kept_numbers(spark: SparkSession, folder: str) -> list[int]:
    """Numbers of the tables that were written whole below a folder."""
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{folder}/*/_SUCCESS")
    found = hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).globStatus(hadoop) or []
    return sorted(int(f.getPath().getParent().getName()) for f in found)


def anti_entropy(stream: DataFrame, peer: DataFrame, protocol: str = "filter_rateless", cfg: SyncConfig | None = None, base: str | None = None) -> tuple[DataFrame, DataFrame]:
    """Parts (payload, nbytes) arrive in batches at A; after each batch A and B synchronise.

    Returns B's final state and the transcripts of all batches. base: the folder of states, log and checkpoint; a run over the
    folder of an earlier one goes on where that ended, and a batch that broke off starts again from the states of the one
    before. Batches may repeat: joins are idempotent.
    """
    cfg = cfg or SyncConfig()
    spark = stream.sparkSession
    base = base or shared_folder(spark, "anti-entropy")
    if not kept_numbers(spark, f"{base}/b"):
        parts = with_digest(peer, segments=cfg.segments or 1)
        snapshot(parts.limit(0), path=f"{base}/a/0")
        snapshot(parts, path=f"{base}/b/0")

    def state(side: str, number: int) -> DataFrame:
        return spark.read.parquet(f"{base}/{side}/{max(n for n in kept_numbers(spark, f'{base}/{side}') if n <= number)}")

    def sync(batch: DataFrame, number: int) -> None:
        arrived = with_digest(batch.select("payload", "nbytes"), segments=cfg.segments or 1)
        before = state("a", number)
        own = snapshot(before.unionByName(arrived.select(*before.columns)).dropDuplicates(["h"]), path=f"{base}/arrived/{number}")
        result = PROTOCOLS[protocol](Replicas.single(own, state("b", number), cfg), cfg)
        result.transcript.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{base}/log/batch={number}")
        for side, new in (("a", result.state_a), ("b", result.state_b)):
            snapshot(new.select(*before.columns), path=f"{base}/{side}/{number + 1}")

    running = stream.writeStream.foreachBatch(sync).option("checkpointLocation", f"{base}/checkpoint").trigger(availableNow=True).start()
    running.awaitTermination()
    numbers = kept_numbers(spark, f"{base}/b")
    return spark.read.parquet(f"{base}/b/{numbers[-1]}"), spark.read.parquet(f"{base}/log")


def decode_stream(cells: DataFrame) -> DataFrame:
    """Difference cells (sid, seg, i, id_sum, check_sum, cnt), in order of i over batches, to DIFF rows, sent once a segment is decoded; its last row has no owner (a null digest would make pandas round the others).

    State per segment: the cells so far and whether it is done. Cells that come again are ignored.
    """

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held, done = state.get if state.exists else ([], False)
        got = {int(c[0]): tuple(map(int, c)) for c in held}
        for frame in frames:
            for row in frame.itertuples(index=False):
                got[int(row.i)] = (int(row.i), int(row.id_sum), int(row.check_sum), int(row.cnt))
        if not done and 0 in got:  # cell 0 tells when all is found; cells that have not come yet or are empty count as empty
            decoder, used = coded.Decoder(), 0
            for i in range(max(got) + 1):
                _, a, b, c = got.get(i, (i, 0, 0, 0))
                used += 1
                if decoder.add(a, b, c):
                    break
            if decoder.done:
                done = True
                rows = [(key[0], key[1], d, "a_only" if s > 0 else "b_only", used, True) for d, s in decoder.found.items()] + [(key[0], key[1], -1, "", used, True)]
                yield pd.DataFrame(rows, columns=["sid", "seg", "d", "owner", "used", "done"])
        state.update(([list(c) for c in sorted(got.values())], done))

    return cells.groupBy("sid", "seg").applyInPandasWithState(step, coded.DIFF, "cells array<array<bigint>>, done boolean", "append", GroupStateTimeout.NoTimeout)


def streamed_difference(ours: DataFrame, theirs: DataFrame, first: int = 256, growth: int = 4) -> DataFrame:
    """DIFF rows of two digest sets (sid, seg, d). Slices of the stream are added to its input, each growth times as far, until cell 0 of all segments is empty.

    The decoder goes on from its checkpoint; segments that are decoded get no more cells.
    """
    spark = ours.sparkSession
    path, base = shared_folder(spark, "cell-slices"), shared_folder(spark, "stream")
    most = max(first, 16 * (ours.count() + theirs.count()))
    segments = snapshot(ours.select("sid", "seg").union(theirs.select("sid", "seg")).distinct(), "segments")
    open_, low, high = segments, 0, first
    while not open_.isEmpty():
        if low >= most:
            raise RuntimeError(f"cells up to {low} leave segments undecoded")
        x, y = (z.join(open_, ["sid", "seg"], "left_semi") for z in (ours, theirs))
        cells = coded.subtract_cells(coded.coded_cells(x, low, high), coded.coded_cells(y, low, high))
        cells.repartitionByRange(4, "i").sortWithinPartitions("i").write.parquet(f"{path}/{high}")
        found = decode_stream(stream_of(spark, path, cells.schema))
        running = found.writeStream.format("parquet").outputMode("append").option("path", f"{base}/found").option("checkpointLocation", f"{base}/checkpoint").trigger(availableNow=True).start()
        running.awaitTermination()
        done = spark.read.schema(coded.DIFF).parquet(f"{base}/found")
        open_ = snapshot(segments.join(done.where("owner = ''"), ["sid", "seg"], "left_anti"), "open")
        low, high = high, high * growth
    return spark.read.schema(coded.DIFF).parquet(f"{base}/found").where("owner != ''") if low else ours.limit(0).selectExpr("sid", "seg", "d", "'' as owner", "0 as used", "true as done")


def fork(state: DataFrame, name: str = "fork") -> DataFrame:
    """A snapshot to synchronise while the state itself takes writes."""
    return snapshot(state, name)


def remerge(lattice: KeyedLattice, state: DataFrame, forked: DataFrame) -> DataFrame:
    return lattice.join(state, forked)


HOUR = "time_bucket(interval '1 hour', ts)"
START = "strftime({}, '%Y-%m-%d %H:%M:%S')"


def started(c: str) -> Column:
    return F.date_format(c, "yyyy-MM-dd HH:mm:ss")


@query(f"select event_type, {START.format(HOUR)} as start, count(*) as n from events group by 1, 2")
def st_tumbling(spark, sf):
    counted = event_stream(spark, sf).withWatermark("ts", "1 hour").groupBy("event_type", F.window("ts", "1 hour")).agg(F.count("*").alias("n"))
    return drained(counted, "complete").select("event_type", started("window.start").alias("start"), "n")


@query(f"select event_type, {START.format(HOUR + ' - interval 1 hour * k')} as start, count(*) as n from events, (values (0), (1)) t(k) group by 1, 2")
def st_sliding(spark, sf):
    counted = event_stream(spark, sf).groupBy("event_type", F.window("ts", "2 hours", "1 hour")).agg(F.count("*").alias("n"))
    return drained(counted, "complete").select("event_type", started("window.start").alias("start"), "n")


@query(f"with g as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) >= interval 30 minutes or lag(ts) over (partition by user_id order by ts) is null then 1 else 0 end as new from events), s as (select user_id, ts, sum(new) over (partition by user_id order by ts rows unbounded preceding) as k from g) select user_id, {START.format('min(ts)')} as start, count(*) as n from s group by user_id, k")
def st_session(spark, sf):
    counted = event_stream(spark, sf).groupBy("user_id", F.session_window("ts", "30 minutes")).agg(F.count("*").alias("n"))
    return drained(counted, "complete").select("user_id", started("session_window.start").alias("start"), "n")


@query("select event_id from events")
def st_dedup(spark, sf):
    """Events that are sent again within a week pass once; ids older than that leave the state."""
    return drained(replayed(spark, sf, latest=True).withWatermark("ts", "7 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id"))


@query("select event_type, count(*) as n from events group by 1")
def st_late(spark, sf):
    """Late and repeated rows join harmlessly: the state is a set of ids, counted at the end."""
    seen = replayed(spark, sf).groupBy("event_type", "event_id").agg(F.count("*").alias("times"))
    return drained(seen, "complete").groupBy("event_type").agg(F.count("*").alias("n"))


@query("select event_id, c_mktsegment from events join customer on user_id = c_custkey")
def st_stream_static(spark, sf):
    return drained(event_stream(spark, sf).join(read(spark, sf, "customer"), F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment"))


@query("select a.event_id as click_id, b.event_id as purchase_id from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts between a.ts and a.ts + interval 1 hour")
def st_stream_stream(spark, sf):
    a = event_stream(spark, sf).where("event_type = 'click'").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("u"), F.col("ts").alias("clicked")).withWatermark("clicked", "2 hours")
    b = event_stream(spark, sf).where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", "ts").withWatermark("ts", "2 hours")
    return drained(a.join(b, F.expr("u = user_id and ts >= clicked and ts <= clicked + interval 1 hour")).select("click_id", "purchase_id"))


@query("select user_id, event_type, event_id % 3 as replica, count(*) as n from events group by all")
def st_lattice_state(spark, sf):
    """Running counts of replicas, joined as they arrive: the greatest of each entry stays."""
    from pyspark.sql import Window

    e = read(spark, sf, "events").withColumn("replica", F.col("event_id") % 3)
    w = Window.partitionBy("user_id", "event_type", "replica").orderBy("ts", "event_id")
    running = e.select("user_id", "event_type", "replica", F.row_number().over(w).cast("bigint").alias("n"), "ts")
    stream = stream_of(spark, files_of(running, "ts", 4, 50), running.schema)
    return drained(stream_state(stream, KeyedLattice("grow_counter", ("user_id", "event_type", "replica"), ("n",))), "complete")


@query("with p as (select *, row_number() over (order by h) as rank, (count(*) over ()) // 2 as c from (" + digests_sql("select distinct payload from (" + items_sql("supplier") + ")") + ")), q as (select *, cast(round(2*0.5*c/1.5) as bigint) as sh from p) select d, case when rank <= c then 'a_only' else 'b_only' end as owner from q where rank > sh and rank <= 2*c - sh")
def st_decode(spark, sf):
    """Cells of a pair's difference streamed slice by slice until decoded."""
    from replica_sync.sources.replicas import make_pair, sides

    a, b = sides(snapshot(make_pair(parts_of(spark, sf, "supplier"), 0.5), "pair"))
    keyed = lambda x: x.withColumn("sid", F.lit(0).cast("bigint")).select("sid", "seg", "d")
    return streamed_difference(keyed(a), keyed(b)).select("d", "owner")


@query("select event_id from events")
def st_anti_entropy(spark, sf):
    """Events arriving in files at one replica, synchronised after every batch with one that had the even ones."""
    items = load_items(spark, sf, "events")
    dated = load_items(spark, sf, "events", ts=F.col("ts").cast("timestamp"))
    path = files_of(dated.select("payload", "nbytes", "ts"), "ts", 3)
    stream = stream_of(spark, path, dated.select("payload", "nbytes", "ts").schema)
    final, _ = anti_entropy(stream, items.where(F.col("part_key").cast("bigint") % 2 == 0).select("payload", "nbytes"))
    return final.select(F.split_part("payload", F.lit("|"), F.lit(1)).cast("bigint").alias("event_id"))
