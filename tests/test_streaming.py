"""Streams that stop and go on."""

from replica_sync.streaming import queries


def test_anti_entropy_goes_on_after_a_restart(spark, tmp_path):
    """Half of the files, an end, then the rest by a new run over the same folder: no part is lost, none is read twice."""
    base, files = f"file://{tmp_path}/sync", f"{tmp_path}/files"
    rows = [(f"part {k}", len(f"part {k}")) for k in range(60)]
    kind = "payload string, nbytes int"
    peer = spark.createDataFrame(rows[50:], kind)

    def arrive(part, number):
        spark.createDataFrame(part, kind).coalesce(1).write.parquet(f"{files}/{number}")

    def go():
        return queries.anti_entropy(queries.stream_of(spark, files, spark.createDataFrame([], kind).schema), peer, "bucketed", base=base)

    arrive(rows[:20], 0)
    first, _ = go()
    assert first.count() == 30
    arrive(rows[15:40], 1)
    final, log = go()
    assert {r["payload"] for r in final.collect()} == {p for p, _ in rows[:40] + rows[50:]}
    assert {r["batch"] for r in log.select("batch").distinct().collect()} == {0, 1}


def test_empty_stream(spark, tmp_path):
    spark.createDataFrame([], "v int").write.parquet(f"{tmp_path}/none")
    stream = spark.readStream.schema("v int").parquet(f"{tmp_path}/none")
    assert queries.drained(stream).count() == 0
    assert queries.drained(stream.groupBy("v").count(), "complete").count() == 0
