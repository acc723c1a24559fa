"""Lattice laws on small states, by brute force."""

from itertools import combinations

import pytest

from replica_sync.operators.lattice import AddWinsSet, PairLattice, grow_counter, grow_map, grow_set, last_writer_register, max_register, two_phase_set, up_down_counter

CASES = {
    "grow_set": (grow_set("x"), "x string", [("p",), ("q",)], [("q",), ("r",)], [("s",)]),
    "grow_counter": (grow_counter("k"), "k string, replica int, n int", [("k", 1, 3), ("k", 2, 1)], [("k", 1, 2), ("k", 3, 7)], [("j", 1, 1)]),
    "up_down": (up_down_counter("k"), "k string, replica int, sign string, n int", [("k", 1, "pos", 3)], [("k", 1, "neg", 2), ("k", 1, "pos", 5)], []),
    "max_register": (max_register("k"), "k string, v int", [("k", 3)], [("k", 4), ("j", 1)], [("j", 2)]),
    "last_writer": (last_writer_register("k"), "k string, ts int, tie int, v string", [("k", 1, 1, "x")], [("k", 1, 2, "y")], [("k", 0, 9, "z")]),
    "map": (grow_map("m", grow_counter("k")), "m string, k string, replica int, n int", [("m", "k", 1, 3)], [("m", "k", 1, 4), ("o", "k", 1, 1)], []),
    "two_phase": (two_phase_set("x"), "x string, removed boolean", [("p", False), ("q", True)], [("p", True)], [("q", False)]),
    "add_wins": (AddWinsSet(), "elem string, replica int, ctr int, live boolean", [("p", 1, 1, True), ("q", 1, 2, False)], [("q", 1, 2, True), ("q", 2, 5, True)], [("p", 1, 1, False)]),
}


def rows(df):
    return sorted(map(tuple, df.collect()))


@pytest.mark.parametrize("name", CASES)
def test_laws(spark, name):
    lattice, schema, *states = CASES[name]
    a, b, c = (spark.createDataFrame(s, schema) for s in states)
    ab = lattice.join(a, b)
    assert rows(ab) == rows(lattice.join(b, a)), "commutative"
    assert rows(lattice.join(ab, c)) == rows(lattice.join(a, lattice.join(b, c))), "associative"
    assert rows(lattice.join(a, a)) == rows(lattice.decompose(a)), "idempotent"
    assert rows(lattice.join(a, a.limit(0))) == rows(lattice.decompose(a)), "bottom"
    assert lattice.leq(a, ab) and lattice.leq(b, ab)
    delta = lattice.delta(a, b)
    assert rows(lattice.join(delta, b)) == rows(ab), "difference"
    parts = delta.collect()
    for fewer in combinations(parts, len(parts) - 1) if parts else ():
        left = spark.createDataFrame(list(fewer), delta.schema)
        assert rows(lattice.join(left, b)) != rows(ab), "minimal"
    own = lattice.decompose(a).collect()
    for fewer in combinations(own, len(own) - 1) if own else ():
        assert rows(lattice.decompose(spark.createDataFrame(list(fewer), lattice.decompose(a).schema))) != rows(lattice.decompose(a)), "irredundant"


def test_add_wins(spark):
    schema = CASES["add_wins"][1]
    lattice = AddWinsSet()
    removed = spark.createDataFrame([("p", 1, 1, False)], schema)
    added = spark.createDataFrame([("p", 1, 1, True), ("p", 2, 1, True)], schema)
    assert rows(lattice.value(lattice.join(removed, added))) == [("p",)]


def test_pairs(spark):
    left, schema, a, b, _ = CASES["grow_set"]
    right, other, x, y, _ = CASES["max_register"]
    pair = PairLattice(left, right)
    p, q = (spark.createDataFrame(a, schema), spark.createDataFrame(x, other)), (spark.createDataFrame(b, schema), spark.createDataFrame(y, other))
    joined = pair.join(p, q)
    assert pair.leq(p, joined) and not pair.leq(joined, p) and pair.decompose(joined).count() == 5


def test_counter_through_a_protocol(spark):
    from replica_sync.protocols import PROTOCOLS, Replicas

    lattice, schema, a, b, _ = CASES["grow_counter"]
    a, b = spark.createDataFrame(a, schema), spark.createDataFrame(b, schema)
    result = PROTOCOLS["rateless"](Replicas.single(lattice.parts(a), lattice.parts(b)))
    assert rows(lattice.from_parts(result.state_b, schema)) == rows(lattice.join(a, b))
