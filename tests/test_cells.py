"""Coded cells: density, prefixes, decoding, agreement of implementations."""

import random

import numpy as np
import pytest

from pyspark.sql import functions as F

from replica_sync.operators import coded
from replica_sync.sources import tables


def cells_of(digests, m):
    out = [[0, 0, 0] for _ in range(m)]
    for d in digests:
        for i in coded.walk(d, m):
            out[i][0] ^= d
            out[i][1] ^= coded.check_of(d)
            out[i][2] += 1
    return out


def test_vector_walk_is_the_scalar_walk():
    r = random.Random(1)
    d = np.array([r.getrandbits(60) for _ in range(200)], dtype=np.uint64)
    got = {int(x): [] for x in d}
    for rows, at in coded.memberships(d, 0, 500):
        for k, i in zip(rows, at):
            got[int(d[k])].append(int(i))
    assert all(got[int(x)] == list(coded.walk(int(x), 500)) for x in d)
    late = {int(x): [] for x in d}
    for rows, at in coded.memberships(d, 100, 500):
        for k, i in zip(rows, at):
            late[int(d[k])].append(int(i))
    assert all(late[k] == [i for i in v if i >= 100] for k, v in got.items())


def test_density():
    r = random.Random(2)
    n = 4000
    hits = sum(1 for _ in range(n) for i in coded.walk(r.getrandbits(60), 41) if i == 40)
    assert abs(hits / n - 1 / 21) < 0.012


@pytest.mark.parametrize("size, low, high", [(1, 1, 1), (50, 1.2, 1.9), (500, 1.25, 1.55)])
def test_cells_per_difference(size, low, high):
    r, used = random.Random(size), []
    for _ in range(6):
        d = [r.getrandbits(60) for _ in range(size)]
        decoder = coded.Decoder()
        for k, cell in enumerate(cells_of(d, 3 * size + 8), 1):
            if decoder.add(*cell):
                break
        assert decoder.done and set(decoder.found) == set(d)
        used.append(k / size)
    assert low <= sum(used) / len(used) <= high


def test_both_signs():
    r = random.Random(3)
    a, b = {r.getrandbits(60) for _ in range(30)}, {r.getrandbits(60) for _ in range(20)}
    shared = {r.getrandbits(60) for _ in range(300)}
    x, y = cells_of(a | shared, 128), cells_of(b | shared, 128)
    decoder = coded.Decoder()
    for p, q in zip(x, y):
        if decoder.add(p[0] ^ q[0], p[1] ^ q[1], p[2] - q[2]):
            break
    assert {d for d, s in decoder.found.items() if s > 0} == a and {d for d, s in decoder.found.items() if s < 0} == b


def test_nothing_is_done_at_once():
    decoder = coded.Decoder()
    assert decoder.add(0, 0, 0)


def test_join_decoder_equals_kernel(spark, sf):
    from replica_sync.plans import engine

    by_joins = engine.QUERIES["peel_rounds_dataframe"][0](spark, sf)
    r = engine.replicas_of(spark, sf, "supplier")
    found = engine.reconcile(engine.digests_of(r.a), engine.digests_of(r.b), engine.SyncConfig()).rows
    both = r.a.unionByName(r.b).select("d", "h").distinct()
    kernel = found.join(both, "d").select("h", "owner")
    assert sorted(map(tuple, by_joins.collect())) == sorted(map(tuple, kernel.collect()))


def test_prefix_consistency(spark, sf):
    from replica_sync.plans import engine

    row = engine.QUERIES["cell_prefix_consistency"][0](spark, sf).first()
    assert row["same"] and row["cells"] == 64


def test_streamed_cells_go_on_until_decoded(spark):
    """334 differences (suppliers at sf0.1) need more than the first 256 cells."""
    from replica_sync.plans import engine
    from replica_sync.sources.replicas import make_pair, sides
    from replica_sync.streaming import queries

    sf = "/root/testdata/sf0.1"
    a, b = ({r["d"] for r in side.collect()} for side in sides(make_pair(engine.tables.parts_of(spark, sf, "supplier"), 0.5)))
    got = sorted((r["d"], r["owner"]) for r in queries.st_decode(spark, sf).collect())
    assert len(got) == 334 and got == sorted([(d, "a_only") for d in a - b] + [(d, "b_only") for d in b - a])


def test_streamed_segments_end_apart(spark):
    from replica_sync.streaming import queries

    r = random.Random(31)
    rows = [[(0, g, r.getrandbits(60)) for _ in range(n)] for g, n in enumerate((0, 3, 40, 9))]
    shared = [(0, 0, r.getrandbits(60)), (0, 2, r.getrandbits(60))]
    kind = "sid bigint, seg int, d bigint"
    ours, theirs = spark.createDataFrame(rows[1] + rows[2] + shared, kind), spark.createDataFrame(rows[3] + shared, kind)
    found = {(x["seg"], x["d"], x["owner"]) for x in queries.streamed_difference(ours, theirs, first=8).collect()}
    assert found == {(g, d, "a_only") for _, g, d in rows[1] + rows[2]} | {(g, d, "b_only") for _, g, d in rows[3]}
    assert queries.streamed_difference(ours.limit(0), theirs.limit(0)).count() == 0


def test_joins_decode_all_or_raise(spark):
    from replica_sync.functions.digest import with_digest

    parts = with_digest(spark.range(400).selectExpr("cast(id as string) as payload", "3 as nbytes", "id")).selectExpr("0L as sid", "0 as seg", "d", "d2", "h", "id")
    ours, theirs = parts.where("id < 250").drop("id"), parts.where("id >= 200").drop("id")
    with pytest.raises(coded.Incomplete):
        coded.peel_by_joins(coded.subtract_cells(coded.md5_cells(ours, 64), coded.md5_cells(theirs, 64)), ours.unionByName(theirs))
    found = coded.difference_by_joins(ours, theirs, first=64).groupBy("owner").count().collect()
    assert {r["owner"]: r["count"] for r in found} == {"a_only": 200, "b_only": 150}


def test_cells_of_many_segments_in_little_memory(spark, sf):
    """A task that may hold two segments' cells sends the sums of others early: the cells are the same."""
    parts = tables.parts_of(spark, sf, "orders", segments=40).withColumn("sid", F.lit(0).cast("bigint"))
    whole, bounded = coded.coded_cells(parts, 0, 64), coded.coded_cells(parts, 0, 64, held_cells=128)
    assert whole.exceptAll(bounded).isEmpty() and bounded.exceptAll(whole).isEmpty()


@pytest.mark.parametrize("n, upto", [(0, 64), (1, 600), (300, 600), (450, 900), (590, 600), (3000, 4800)])
def test_rounds_decode_as_one_cell_at_a_time(n, upto):
    """The same digests, owners and cells used, decodable or not."""
    import numpy as np

    r = np.random.default_rng(n)
    d, sign = r.integers(0, 1 << 60, n).astype(np.uint64), r.choice([-1, 1], n)
    ids, checks, counts = np.zeros(upto, dtype=np.uint64), np.zeros(upto, dtype=np.uint64), np.zeros(upto, dtype=np.int64)
    for rows, at in coded.memberships(d, 0, upto):
        np.bitwise_xor.at(ids, at, d[rows])
        np.bitwise_xor.at(checks, at, coded.checks_of(d)[rows])
        np.add.at(counts, at, sign[rows])
    cells = ids.astype(np.int64), checks.astype(np.int64), counts
    one, all_ = coded.decoded(*cells), coded.decoded_by_rounds(*cells)
    assert dict(zip(*one[:2])) == dict(zip(*all_[:2])) and one[2:] == all_[2:] and len(all_[0]) in (0, n)
    assert one[3] == (n != 590)  # cells for more than nine tenths of themselves do not decode
