"""The facade, SQL functions, peers and streams beyond what queries cover."""

from pyspark.sql import functions as F

from replica_sync.plans.session import SyncSession
from replica_sync.sources import tables


def test_session(spark, sf):
    items = tables.load_items(spark, sf, "supplier")
    session = SyncSession(spark)
    session.replica("a", items.where("cast(part_key as int) <= 8"))
    session.replica("b", items.where("cast(part_key as int) >= 3"))
    rows = session.compare("a", "b", ["state_driven", "filter_rateless"]).collect()
    assert all(r["apart"] == 0 for r in rows)
    assert "filter" in session.explain_sync("a", "b") or session.explain_sync("a", "b")
    assert session.advise("a", "b").protocol
    session.synchronize("a", "b", "auto")
    assert session.replicas["a"].count() == session.replicas["b"].count() == items.count()


def test_sql_functions(spark, sf):
    SyncSession(spark)
    tables.load_items(spark, sf, "region").createOrReplaceTempView("items")
    rows = spark.sql("select part_digest(payload) as d, bucket_of(payload, 7) as b, filter_position(10, 3, 2, 8) as p from items").collect()
    assert all(r["d"] % 7 == r["b"] and r["p"] == 0 for r in rows)
    assert spark.sql("select i.i from (select part_digest('x') as d) t, lateral coded_cells(t.d, 0, 100) i").where("i = 0").count() == 1
    assert spark.sql("""select * from decompose_json('{"k": 1, "j": 2}')""").count() == 2


def test_fork_and_remerge(spark):
    from replica_sync.operators.lattice import grow_set
    from replica_sync.streaming.queries import fork, remerge

    lattice = grow_set("payload")
    state = spark.createDataFrame([("a",), ("b",)], "payload string")
    forked = fork(state)
    state = lattice.mutate(state, spark.createDataFrame([("c",)], "payload string"))
    synced = lattice.join(forked, spark.createDataFrame([("d",)], "payload string"))
    assert remerge(lattice, state, synced).count() == 4


def test_similarities(spark):
    from replica_sync.plans.gossip import partners, similarities

    rows = spark.createDataFrame([("x", "1"), ("x", "2"), ("y", "2"), ("z", "3")], "peer string, h string")
    assert similarities(rows) == {("x", "y"): 0.5, ("x", "z"): 0.0, ("y", "z"): 0.0}
    assert partners(["x", "y", "z"], "ring", 0) == [("x", "y")]
    assert partners(["x", "y", "z"], "topology", 0, topology={"x": ["z"]}) == [("x", "z")]


def test_bucket_digest_kinds_agree_on_mismatch(spark, sf):
    from replica_sync.operators.buckets import bucket_digests, mismatched, with_bucket

    parts = tables.parts_of(spark, sf, "supplier").withColumn("sid", F.lit(0).cast("bigint"))
    a, b = (with_bucket(p, 5) for p in (parts, parts.where("d % 3 != 0")))
    found = [sorted(r["bucket"] for r in mismatched(bucket_digests(a, how), bucket_digests(b, how)).collect()) for how in ("ordered", "xor")]
    assert found[0] == found[1]


def test_gossip_raises_where_peers_still_differ(spark):
    import pytest

    from replica_sync.functions.digest import with_digest
    from replica_sync.plans.gossip import gossip

    rows = spark.createDataFrame([(p, f"{p} has this") for p in "abc"], "peer string, payload string").selectExpr("*", "octet_length(payload) as nbytes")
    with pytest.raises(RuntimeError, match="still differ"):
        gossip(with_digest(rows), "topology", most_rounds=1, topology={"a": ["b"]})
    states, _ = gossip(with_digest(rows), "topology", topology={"a": ["b"], "b": ["c"]})
    assert states.count() == 9
