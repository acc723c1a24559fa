"""Convergence, accounting and the paper's worked examples."""

import pytest
from pyspark.sql import functions as F

from replica_sync.functions.digest import with_digest
from replica_sync.functions.wire import SyncConfig
from replica_sync.operators import membership
from replica_sync.plans import engine, metrics
from replica_sync.protocols import PROTOCOLS, Replicas
from replica_sync.sources import replicas, tables
from replica_sync.sources.tables import snapshot

EXACT = [p for p in PROTOCOLS if p != "filter_only"]


@pytest.fixture(scope="module")
def pairs(spark, sf):
    parts = snapshot(tables.parts_of(spark, sf, "customer"))
    return {s: snapshot(replicas.make_pair(parts, s)) for s in (0.0, 0.5, 1.0)}


def session(pair, **options):
    cfg = SyncConfig(**options)
    return Replicas.single(*replicas.sides(pair), cfg), cfg


@pytest.mark.parametrize("protocol", EXACT)
@pytest.mark.parametrize("s", [0.0, 0.5, 1.0])
def test_converges_and_accounts(pairs, protocol, s):
    r, cfg = session(pairs[s])
    result = PROTOCOLS[protocol](r, cfg)
    assert metrics.converged(result).first()["apart"] == 0
    row = metrics.summarise(result.transcript).first()
    required = metrics.required_bytes(r).first()
    assert row["required_bytes"] == (required["required_bytes"] if required else 0)
    assert row["total_bytes"] == row["metadata_bytes"] + row["redundant_bytes"] + row["required_bytes"]
    union = r.a.unionByName(r.b).select("h").distinct().count()
    assert result.state_a.count() == union == result.state_b.count()


@pytest.mark.parametrize("protocol, rtt", [("state_driven", 1.0), ("bucketed", 1.5), ("filter_only", 1.5), ("filter_bucketed", 2.0), ("rateless", 1.5), ("filter_rateless", 2.0)])
def test_round_trips(pairs, protocol, rtt):
    r, cfg = session(pairs[0.5])
    assert metrics.summarise(PROTOCOLS[protocol](r, cfg).transcript).first()["rtt"] == rtt


def test_segments_give_the_same_states(pairs):
    one, cfg1 = session(pairs[0.5])
    many, cfg8 = session(pairs[0.5], segments=8)
    a = PROTOCOLS["filter_rateless"](one, cfg1).states().drop("sid").collect()
    b = PROTOCOLS["filter_rateless"](many, cfg8).states().drop("sid").collect()
    assert sorted(a) == sorted(b)


def test_equal_sets_cost_one_cell(pairs):
    r, cfg = session(pairs[1.0])
    assert metrics.summarise(PROTOCOLS["rateless"](r, cfg).transcript).first()["total_bytes"] == cfg.wire.cell


@pytest.mark.parametrize("protocol", EXACT)
def test_one_side_empty(pairs, protocol):
    pair = pairs[0.0].where("side = 'a'")
    r, cfg = session(pair)
    result = PROTOCOLS[protocol](r, cfg)
    assert result.state_b.count() == pair.count() == result.state_a.count()


def test_filters_alone_leave_their_false_positives(pairs):
    r, cfg = session(pairs[0.0], eps=0.25)
    result = PROTOCOLS["filter_only"](r, cfg)
    apart = metrics.converged(result).first()["apart"]
    assert apart == result.details.count() > 0


def test_unequal_sizes(spark, sf):
    parts = tables.parts_of(spark, sf, "supplier")
    a, b = parts.orderBy("h").limit(1), parts
    result = PROTOCOLS["filter_rateless"](Replicas.single(a, b))
    assert metrics.converged(result).first()["apart"] == 0 and result.state_a.count() == parts.count()


def test_replayed_messages_change_nothing(pairs):
    from replica_sync.protocols.base import merged

    r, cfg = session(pairs[0.5])
    result = PROTOCOLS["rateless"](r, cfg)
    again = merged(result.state_a, result.state_a, r.b)
    assert again.count() == result.state_a.count()


def test_steps_read_only_their_own_replica(pairs):
    """The filter that A sends comes from A's snapshot alone."""
    a, b = (snapshot(x) for x in replicas.sides(pairs[0.5]))
    r = Replicas.single(a, b)
    files = set(membership.filter_words(r.a, membership.shaped(r.a, r.sessions)).inputFiles())
    assert files and not files & set(b.inputFiles())


def test_ten_buckets(spark, sf):
    row = engine.QUERIES["ten_bucket_case"][0](spark, sf).first()
    assert (row["sent"], row["needed"], row["overhead"]) == (100, 10, 10.0)


def test_filter_shapes():
    assert membership.filter_shape_bits(10_000, 8, 5) == (80_000, 5)
    m, k = membership.filter_shape(10_000, 0.01)
    assert (m, k) == (95851, 7)


def test_no_false_negatives(spark, sf):
    r = engine.replicas_of(spark, sf, "supplier", s=0.5)
    com, excl = membership.split_by_filter(r.a, membership.build_filter(r.a, r.sessions), 7)
    assert excl.isEmpty() and com.count() == r.a.count()


def test_one_filter_for_all_segments(spark, sf, monkeypatch):
    """As many segments as a large table has: the queries that SQL describes with one filter and one stream of cells give the same rows."""
    import duckdb

    from replica_sync.functions import wire

    monkeypatch.setattr(wire, "SEGMENT_PARTS", 60)
    assert wire.segments_for(500) == 9
    con = duckdb.connect()
    for t in ("events", "orders"):
        con.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    for name in ("cell_subtract", "filter_words", "filter_split_a", "filter_split_b", "filter_only_residual", "filter_only_transcript", "filter_bucketed_transcript", "filter_rateless_false_positives", "filter_rateless_payload", "filter_fpr_8bits"):
        run, sql = engine.QUERIES[name]
        df = run(spark, sf)
        found = con.sql(sql)
        want = sorted(tuple(r[found.columns.index(c)] for c in df.columns) for r in found.fetchall())
        assert sorted(map(tuple, df.collect())) == want, name


def test_filter_of_many_blocks(spark):
    """Bits of a part lie in several blocks; a session without a filter has no hits."""
    rows = spark.range(40000).select(F.col("id").cast("string").alias("payload"), (F.col("id") % 2).alias("sid"))
    parts = with_digest(rows, segments=5)
    sessions = spark.createDataFrame([(0, 1e-6), (1, 0.01)], "sid bigint, eps double")
    held = snapshot(membership.build_filter(parts.where("cast(payload as int) < 20000 and sid = 0"), sessions))
    assert held.count() == 5
    hits = {(r["sid"], int(r["payload"])) for r in membership.probed(parts, held).where("hit").collect()}
    assert hits == {(0, i) for i in range(0, 20000, 2)}


def test_three_elements_need_all(spark):
    from replica_sync.operators.lattice import grow_set

    lattice = grow_set("payload")
    state = spark.createDataFrame([("a",), ("b",), ("c",)], "payload string")
    parts = lattice.decompose(state)
    assert parts.count() == 3
    for x in "abc":
        fewer = lattice.compose(parts.where(F.col("payload") != x))
        assert lattice.leq(fewer, state) and not lattice.leq(state, fewer)


def test_message_directory_replays(spark):
    channel = tables.MessageDirectory(spark)
    channel.send("filter", spark.range(3))
    channel.send("cells", spark.range(2))
    assert channel.receive(1, "filter").count() == 3 and channel.receive(2, "cells").count() == 2


def test_flagship(spark, sf):
    row = engine.flagship(spark, sf).first()
    assert row["apart"] == 0 and row["redundant_bytes"] == 0 and abs(row["similarity"] - 0.75) < 0.01


def forged(spark, rows):
    """Parts of given payload, d and d2: (payload, d, d2)."""
    return spark.createDataFrame([(p, len(p), F_H.format(d, e), d, e) for p, d, e in rows], "payload string, nbytes int, h string, d bigint, d2 bigint")


F_H = "{:016x}{:016x}"


@pytest.mark.parametrize("protocol", ["rateless", "filter_rateless"])
def test_colliding_digests_converge(spark, protocol):
    """Equal d on both sides with different d2 (hidden by the cells), and twice on one side (never decodes)."""
    shared = [(f"s{k}", 1000 + 7919 * k, 5000 + 104729 * k) for k in range(40)]
    across = forged(spark, [*shared, ("x", 77, 10**12)]), forged(spark, [*shared, ("y", 77, 10**13), ("z", 78, 10**14)])
    within = forged(spark, [*shared, ("x", 77, 10**12), ("y", 77, 10**13)]), forged(spark, shared)
    for a, b in (across, within):
        result = PROTOCOLS[protocol](Replicas.single(a, b), SyncConfig())
        assert metrics.converged(result).first()["apart"] == 0
        assert result.state_a.count() == a.unionByName(b).select("h").distinct().count()


@pytest.mark.parametrize("filtered, plain", [("filter_rateless", "rateless"), ("filter_bucketed", "bucketed"), ("filter_bucketed_rateless", "bucketed_rateless")])
def test_no_filter_is_the_plain_protocol(pairs, filtered, plain):
    r, _ = session(pairs[0.5])
    bytes_of = lambda p, cfg: metrics.summarise(PROTOCOLS[p](r, cfg).transcript).drop("protocol").collect()
    assert bytes_of(filtered, SyncConfig(eps=0)) == bytes_of(plain, SyncConfig())


def test_settings_of_the_call_hold(pairs):
    r, _ = session(pairs[0.5], eps=0.01)
    sent = lambda cfg: PROTOCOLS["filter_rateless"](r, cfg).transcript.where("kind = 'filter'").first()["metadata_bytes"]
    assert sent(SyncConfig(eps=0.25)) < sent(SyncConfig(eps=0.1)) < sent(SyncConfig()) == sent(SyncConfig(eps=0.01))


def test_similarity_of_nothing(spark, pairs):
    none = replicas.sides(pairs[0.5].limit(0))
    assert replicas.jaccard(*none).first()["similarity"] == 1.0


def test_no_cartesian_product(spark, pairs):
    """Not even with broadcasts off."""
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        for protocol in EXACT:
            result = PROTOCOLS[protocol](*session(pairs[0.5]))
            for df in (result.transcript, result.state_a, result.state_b):
                assert "CartesianProduct" not in df._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)


def test_long_uniform_strings(spark, sf):
    rows = replicas.uniform_strings(tables.load_items(spark, sf, "supplier"), 300, 400).select(F.length("payload").alias("n")).collect()
    assert all(300 <= r["n"] <= 400 for r in rows) and max(r["n"] for r in rows) > 330
