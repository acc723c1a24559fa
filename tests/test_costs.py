"""What the engine is charged for, and what fixed tables cost when they fail."""

from pyspark.sql import functions as F

from replica_sync.functions.wire import SyncConfig
from replica_sync.plans import catalogue
from replica_sync.plans.metrics import engine_cost
from replica_sync.protocols import Replicas
from replica_sync.protocols.exact import digests_of
from replica_sync.related import fixed_table
from replica_sync.sources import replicas, tables


def pair(spark, sf, segments):
    parts = replicas.make_pair(tables.parts_of(spark, sf, "events"), 0.9)
    return Replicas.single(*replicas.sides(tables.snapshot(parts, "pair")), SyncConfig(segments=segments))


def test_cost_of_stages(spark):
    rows = engine_cost(spark, lambda: spark.range(0, 1000, 1, 4).repartition(3, "id").write.format("noop").mode("overwrite").save()).collect()
    assert len(rows) == 2 and [r.tasks for r in rows][0] == 4
    assert sum(r.shuffle_rows for r in rows) == 1000 == rows[1].rows_read and rows[0].shuffle_bytes > 0
    assert engine_cost(spark, lambda: None).count() == 0


def test_cost_when_the_store_lets_go_of_skipped_stages(spark):
    """A store that keeps few stages forgets skipped ones first; what ran still counts, and what ran and is forgotten raises."""
    import os
    import subprocess
    import sys

    code = """
from pyspark.sql import SparkSession
from replica_sync.plans.metrics import engine_cost
spark = SparkSession.builder.master("local[2]").config("spark.ui.enabled", "false").config("spark.ui.retainedStages", "8").getOrCreate()
sc = spark.sparkContext
pairs = sc.parallelize(range(100), 2).map(lambda x: (x % 5, x)).groupByKey(2)
pairs.count()
again = lambda n: lambda: [pairs.count() for _ in range(n)]
rows = engine_cost(spark, again(5)).collect()
assert len(rows) == 5 and all(r.tasks == 2 for r in rows), rows
try:
    engine_cost(spark, again(30))
except RuntimeError as e:
    assert "retainedStages" in str(e)
else:
    raise AssertionError("stages went missing unnoticed")
"""
    ran = subprocess.run([sys.executable, "-c", code], env=dict(os.environ), capture_output=True, text=True, timeout=300)
    assert ran.returncode == 0, ran.stderr[-3000:]


def test_only_failed_tables_are_sent_again(spark, sf):
    r = pair(spark, sf, 4)
    found, attempts = fixed_table.with_restarts(digests_of(r.a), digests_of(r.b), 16)
    both = digests_of(r.a).select("seg", "d").distinct()
    other = digests_of(r.b).select("seg", "d").distinct()
    want = {(x.seg, x.d, "a_only") for x in both.exceptAll(other).collect()} | {(x.seg, x.d, "b_only") for x in other.exceptAll(both).collect()}
    assert {(x.seg, x.d, x.owner) for x in found.rows.collect()} == want and attempts > 1
    # by hand: a segment pays each size up to the first that decodes
    left, size, cells = set(range(4)), 16, 0
    while left:
        tried = fixed_table.fixed_table_attempt(digests_of(r.a), digests_of(r.b), size).where(F.col("d").isNull()).collect()
        cells += size * len(left)
        left -= {x.seg for x in tried if x.done}
        size *= 2
    assert found.used.collect()[0].cells == cells


def test_larger_tables_fail_less(spark, sf):
    rates = [x.failure_rate for x in catalogue.queries()["filter_fixed_table_failures"](spark, sf).orderBy("slack").collect()]
    assert all(0 <= x <= 1 for x in rates) and rates == sorted(rates, reverse=True) and rates[-1] < 0.2


def test_sweep_by_few_sessions_at_a_time(spark, sf, monkeypatch):
    """One session under way at a time: the same rows, no payload and nothing of the sessions left in the shared folder."""
    from pathlib import Path

    from replica_sync.plans import workloads

    parts = tables.snapshot(tables.parts_of(spark, sf, "supplier"))
    rows = lambda: sorted(map(tuple, workloads.sweep(parts, ["bucketed", "filter_rateless"], [0.0, 0.75], [0.01], [1.0]).collect()))
    together = rows()
    monkeypatch.setattr(workloads, "SWEPT_PARTS", 1)
    base = Path(spark.conf.get("spark.checkpoint.dir").removeprefix("file://"))
    before = {p.name for p in base.iterdir()}
    assert rows() == together
    left = {p.name for p in base.iterdir()} - before
    assert len([n for n in left if n.startswith("metrics-")]) == 4 and all(n.startswith(("metrics-", "ranked-")) for n in left)
    for folder in left:
        if folder.startswith("ranked-"):
            assert spark.read.parquet(f"file://{base / folder}").where("payload is not null").isEmpty()


def test_sweep_with_filters_in_several_segments_as_its_sql(spark, sf):
    """Segments of a replica share one filter: bytes by w2_bytes' SQL, however many there are."""
    import duckdb

    from replica_sync.plans import engine, workloads

    con = duckdb.connect()
    con.sql(f"create view events as select * from '{sf}/events.parquet'")
    want = {tuple(r) for r in con.sql(engine.filtered_sweep_sql([0.45], [0.25], [0.2])).fetchall() if r[1] == "filter_bucketed"}
    swept = workloads.sweep(engine.events_parts(spark, sf), ["filter_bucketed"], [0.45], [0.25], [0.2], SyncConfig(segments=6))
    assert {tuple(r) for r in engine.told_bytes(swept, "filter_bucketed").collect()} == want and len(want) == 1


def test_sweep_with_cells_in_several_segments_as_its_sql(spark, sf):
    """The same for the protocols whose filters are followed by cells: parts and buckets are reconciled by segment, filters are not."""
    import duckdb

    from replica_sync.plans import engine, workloads

    protocols = ["filter_rateless", "filter_bucketed_rateless"]
    con = duckdb.connect()
    con.sql(f"create view events as select * from '{sf}/events.parquet'")
    want = {tuple(r) for r in con.sql(engine.filtered_sweep_sql([0.45], [0.25], [0.2])).fetchall() if r[1] in protocols}
    swept = workloads.sweep(engine.events_parts(spark, sf), protocols, [0.45], [0.25], [0.2], SyncConfig(segments=6))
    assert {tuple(r) for r in engine.told_bytes(swept, "filter_bucketed").collect()} == want and len(want) == 2


def test_bucket_digests_are_made_once_and_lie_by_segment(spark, sf, monkeypatch):
    """Slices of the cell stream read what was kept of both sides, and a segment's cells leave one task."""
    from replica_sync.protocols import base, exact

    pair = tables.snapshot(replicas.make_pair(tables.parts_of(spark, sf, "orders"), 0.5))
    r = Replicas.single(*replicas.sides(pair))
    counts = exact.counts_by(r.a, r.sessions)
    made = spark.sparkContext.accumulator(0)

    def noted(h):
        made.add(1)
        return h

    def placed(digests, low, high, coded_cells=base.coded.coded_cells):
        tasks = digests.select("sid", "seg", F.spark_partition_id().alias("task")).distinct().groupBy("sid", "seg").count()
        spread.append(tasks.agg(F.max("count")).first()[0])
        return coded_cells(digests, low, high)

    spread = []
    monkeypatch.setattr(base.coded, "coded_cells", placed)
    theirs = exact.numbered(r.b.withColumn("h", F.udf(noted, "string")("h")), counts)
    bad, _ = exact.bucket_reconciled(exact.numbered(r.a, counts), theirs, counts, SyncConfig(segments=6))
    want = exact.mismatched(*(exact.bucket_digests(exact.numbered(x, counts)) for x in (r.a, r.b)))
    assert sorted(map(tuple, bad.collect())) == sorted(map(tuple, want.collect())) and not want.isEmpty()
    assert made.value == r.b.count()
    assert len(spread) > 2 and max(spread) == 1


def test_steps_of_a_sweep_use_the_places_of_parts(spark, sf):
    """Joins of parts and digests of buckets exchange and sort nothing again; what a sweep kept and set is gone at its end."""
    from replica_sync.operators.buckets import bucket_digests, mismatched
    from replica_sync.protocols import base, exact

    r = pair(spark, sf, 3)
    counts = tables.snapshot(exact.counts_by(r.a, r.sessions), "counts")
    before = {name: spark.conf.get(name) for name in tables.BY_PLACE}
    steps = lambda r, a, b: {"without": base.without(r.a, r.b), "within": base.within(a, b), "mismatched": mismatched(bucket_digests(a), bucket_digests(b))}
    rows = lambda df: sorted(map(tuple, df.select("sid", df.columns[1], *(["h"] if "h" in df.columns else [])).collect()))
    want = {name: rows(df) for name, df in steps(r, exact.numbered(r.a, counts), exact.numbered(r.b, counts)).items()}
    assert want["without"] and want["within"] and want["mismatched"]
    with tables.placing(spark, 300_000):
        found = steps(r.by_segment(), exact.by_bucket(r.a, counts), exact.by_bucket(r.b, counts))
        for name, df in found.items():
            assert rows(df) == want[name]
            plan = df._jdf.queryExecution().sparkPlan().toString()
            assert "InMemoryTableScan" in plan and "SortMergeJoin" not in plan, name
        kept = list(tables._places[-1][1])
        assert len(kept) == 4 and all(df.storageLevel.useDisk for df in kept)
    assert not any(df.storageLevel.useDisk for df in kept)
    assert {name: spark.conf.get(name) for name in tables.BY_PLACE} == before
