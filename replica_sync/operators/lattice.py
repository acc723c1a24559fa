"""Join-semilattices as tables: decomposition into irreducible parts, join, order, minimal difference.

Most lattices are keyed: a state has one row per key, rows of a key are totally ordered, the join keeps
the greatest row of each key, and every row is one part. Maps over a lattice put the map's key before the
inner keys. Add-wins sets and pairs have their own rules.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from replica_sync.functions.digest import with_digest


@dataclass(frozen=True)
class KeyedLattice:
    """keys: what identifies a part; order: columns that grow (empty: presence is all there is)."""

    name: str
    keys: tuple[str, ...]
    order: tuple[str, ...] = ()

    @property
    def columns(self) -> list[str]:
        return [*self.keys, *self.order]

    def decompose(self, state: DataFrame) -> DataFrame:
        """One row per irreducible part: the irredundant decomposition."""
        return self.compose(state)

    def compose(self, parts: DataFrame) -> DataFrame:
        """The least upper bound of any parts, in one exchange with partial aggregates."""
        if not self.order:
            return parts.select(*self.keys).distinct()
        if len(self.order) == 1:
            return parts.groupBy(*self.keys).agg(F.max(self.order[0]).alias(self.order[0]))
        best = parts.groupBy(*self.keys).agg(F.max(F.struct(*self.order)).alias("__best"))
        return best.select(*self.keys, *[F.col(f"__best.{c}").alias(c) for c in self.order])

    def join(self, a: DataFrame, b: DataFrame) -> DataFrame:
        return self.compose(a.select(*self.columns).unionByName(b.select(*self.columns)))

    def mutate(self, state: DataFrame, changes: DataFrame) -> DataFrame:
        """Inflationary: whatever the changes, the result is not below the state."""
        return self.join(state, changes)

    def delta(self, a: DataFrame, b: DataFrame) -> DataFrame:
        """The parts of a that b does not cover: the smallest state that lifts b to the join."""
        own = self.decompose(a).alias("own")
        other = self.decompose(b).alias("other")
        covered: Column = F.lit(True)
        for k in self.keys:
            covered &= F.col(f"own.{k}").eqNullSafe(F.col(f"other.{k}"))
        if self.order:
            covered &= F.struct(*[F.col(f"other.{c}") for c in self.order]) >= F.struct(*[F.col(f"own.{c}") for c in self.order])
        return own.join(other, covered, "left_anti").select(*self.columns)

    def leq(self, a: DataFrame, b: DataFrame) -> bool:
        return self.delta(a, b).isEmpty()

    def parts(self, state: DataFrame, segments: int = 1) -> DataFrame:
        """The decomposition as payload strings with digests, for the protocols."""
        text = F.to_json(F.struct(*self.columns), {"ignoreNullFields": "false"})
        rows = self.decompose(state).select(text.alias("payload")).withColumn("nbytes", F.octet_length("payload"))
        return with_digest(rows, segments=segments)

    def from_parts(self, parts: DataFrame, schema: str) -> DataFrame:
        return self.compose(parts.select(F.from_json("payload", schema).alias("row")).select("row.*"))


def grow_set(*columns: str) -> KeyedLattice:
    return KeyedLattice("grow_set", columns)


def grow_counter(*key: str, replica: str = "replica", n: str = "n") -> KeyedLattice:
    """One entry per replica, the greater count wins."""
    return KeyedLattice("grow_counter", (*key, replica), (n,))


def up_down_counter(*key: str, replica: str = "replica") -> KeyedLattice:
    """Two grow-only counters: rows are (key, replica, sign, n)."""
    return KeyedLattice("up_down_counter", (*key, replica, "sign"), ("n",))


def max_register(*key: str, v: str = "v") -> KeyedLattice:
    return KeyedLattice("max_register", key, (v,))


def last_writer_register(*key: str, ts: str = "ts", tie: str = "tie", v: str = "v") -> KeyedLattice:
    """Later time wins, then the tie column; the value is a function of both."""
    return KeyedLattice("last_writer_register", key, (ts, tie, v))


def grow_map(key: str | Sequence[str], inner: KeyedLattice) -> KeyedLattice:
    """A map whose values are states of inner; maps of maps nest the keys."""
    outer = (key,) if isinstance(key, str) else tuple(key)
    return KeyedLattice(f"grow_map[{inner.name}]", (*outer, *inner.keys), inner.order)


def two_phase_set(*columns: str, removed: str = "removed") -> KeyedLattice:
    """Added, then perhaps removed for good: the flag grows."""
    return KeyedLattice("two_phase_set", columns, (removed,))


class AddWinsSet:
    """Rows (elem, replica, ctr, live): live adds, and adds seen but since removed (their dots stay in the context).

    Joined, a dot is live unless one side has seen it dead; so an add concurrent with a removal wins. A
    removal is a part too: the dead dot.
    """

    columns = ("elem", "replica", "ctr", "live")
    _keyed = KeyedLattice("add_wins_set", ("elem", "replica", "ctr"), ("dead",))

    def _dead(self, state: DataFrame) -> DataFrame:
        return state.select("elem", "replica", "ctr", (~F.col("live")).alias("dead"))

    def _live(self, state: DataFrame) -> DataFrame:
        return state.select("elem", "replica", "ctr", (~F.col("dead")).alias("live"))

    def decompose(self, state: DataFrame) -> DataFrame:
        return self._live(self._keyed.decompose(self._dead(state)))

    def join(self, a: DataFrame, b: DataFrame) -> DataFrame:
        return self._live(self._keyed.join(self._dead(a), self._dead(b)))

    def delta(self, a: DataFrame, b: DataFrame) -> DataFrame:
        return self._live(self._keyed.delta(self._dead(a), self._dead(b)))

    def leq(self, a: DataFrame, b: DataFrame) -> bool:
        return self.delta(a, b).isEmpty()

    def value(self, state: DataFrame) -> DataFrame:
        return state.where("live").select("elem").distinct()


class PairLattice:
    """Two lattices side by side; parts carry the side they are of."""

    def __init__(self, left, right):
        self.left, self.right = left, right

    def join(self, a: tuple[DataFrame, DataFrame], b: tuple[DataFrame, DataFrame]) -> tuple[DataFrame, DataFrame]:
        return self.left.join(a[0], b[0]), self.right.join(a[1], b[1])

    def delta(self, a: tuple[DataFrame, DataFrame], b: tuple[DataFrame, DataFrame]) -> tuple[DataFrame, DataFrame]:
        return self.left.delta(a[0], b[0]), self.right.delta(a[1], b[1])

    def decompose(self, state: tuple[DataFrame, DataFrame]) -> DataFrame:
        """(side, part): parts of either side as JSON."""

        def tagged(side: str, lattice, rows: DataFrame) -> DataFrame:
            return lattice.decompose(rows).select(F.lit(side).alias("side"), F.to_json(F.struct("*")).alias("part"))

        return tagged("left", self.left, state[0]).unionByName(tagged("right", self.right, state[1]))

    def leq(self, a, b) -> bool:
        return self.left.leq(a[0], b[0]) and self.right.leq(a[1], b[1])
