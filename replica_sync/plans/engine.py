"""Queries of lattices, pairs, protocols, related techniques, cost model, peers and workloads, with their SQL."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from replica_sync.functions.digest import segment_of, with_digest
from replica_sync.functions.wire import SyncConfig, segments_for
from replica_sync.operators import buckets, coded, lattice, membership
from replica_sync.plans import costmodel, gossip, workloads
from replica_sync.plans.metrics import converged, crossover, engine_cost, redundancy_peak, reduction, summarise
from replica_sync.protocols import PROTOCOLS, Replicas, SyncResult
from replica_sync.protocols.base import reconcile
from replica_sync.protocols.exact import counts_by, digests_of, numbered
from replica_sync.protocols.filtered import filter_split
from replica_sync.related import blocks, deltas, estimators, fixed_table, tree
from replica_sync.sources import replicas, tables
from replica_sync.sources.tables import digests_sql, items_sql, read, snapshot

QUERIES: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str | None]] = {}
LN2 = math.log(2)
FULL = lattice.grow_set("payload")


def query(name: str, sql: str | None = None):
    def register(f: Callable[[SparkSession, str], DataFrame]):
        QUERIES[name] = (f, sql)
        return f

    return register


def add(name: str, f: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = (f, sql)


# ---- canonical items ----
for _t in ("events", "lineitem", "orders", "customer", "part", "supplier", "region", "nation", "benchmark", "pages", "conversations"):
    add(f"items_{_t}", lambda spark, sf, t=_t: tables.load_items(spark, sf, t), f"select part_key, payload, octet_length(encode(payload)) as nbytes from ({items_sql(_t)})")
add("items_documents_distinct", lambda spark, sf: tables.parts_of(spark, sf, "documents").select("payload", "nbytes", "h", "d", "d2"), digests_sql(f"select distinct payload from ({items_sql('documents')})"))
add("digest_families", lambda spark, sf: tables.load_items(spark, sf, "supplier").select("payload", *[F.expr("md5(cast(payload as binary))").alias("md5"), F.sha2(F.col("payload").cast("binary"), 256).alias("sha2")]), f"select payload, md5(payload) as md5, sha256(payload) as sha2 from ({items_sql('supplier')})")

# ---- lattices ----
EV = items_sql("events")
NATURAL_A, NATURAL_B = f"select payload from ({EV}) where part_key in (select cast(event_id as varchar) from events where ts < timestamp '2024-01-21')", f"select payload from ({EV}) where part_key in (select cast(event_id as varchar) from events where ts >= timestamp '2024-01-11')"


def natural(spark, sf):
    return replicas.sides(replicas.natural_events(spark, sf))


add("growset_join", lambda spark, sf: FULL.join(*natural(spark, sf)), f"{NATURAL_A} union {NATURAL_B}")
add("growset_delta_ab", lambda spark, sf: FULL.delta(*natural(spark, sf)), f"{NATURAL_A} except {NATURAL_B}")
add("growset_delta_ba", lambda spark, sf: FULL.delta(*reversed(natural(spark, sf))), f"{NATURAL_B} except {NATURAL_A}")
add("decompose_growset", lambda spark, sf: FULL.decompose(read(spark, sf, "region").where("r_regionkey < 3").select(F.col("r_name").alias("payload"))), "select r_name as payload from region where r_regionkey < 3")


@query("growset_leq", f"select 'join' as below, (select count(*) from ({NATURAL_A} except ({NATURAL_A} union {NATURAL_B}))) = 0 as holds union all select 'other', (select count(*) from ({NATURAL_A} except {NATURAL_B})) = 0")
def growset_leq(spark, sf):
    a, b = natural(spark, sf)
    return spark.createDataFrame([("join", FULL.leq(a, FULL.join(a, b))), ("other", FULL.leq(a, b))], "below string, holds boolean")


def two(spark, sf, make):
    """The same lattice state from two overlapping halves of events."""
    e = read(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
    return make(e.where("ts < timestamp_ntz'2024-01-21 00:00:00'")), make(e.where("ts >= timestamp_ntz'2024-01-11 00:00:00'"))


SQL_A, SQL_B = "(select * from events where ts < timestamp '2024-01-21')", "(select * from events where ts >= timestamp '2024-01-11')"
COUNTER = lattice.grow_counter("user_id", "event_type")


def counter_state(e):
    return e.groupBy("user_id", "event_type", (F.col("event_id") % 3).alias("replica")).agg(F.count("*").alias("n"))


def counter_sql(src):
    return f"select user_id, event_type, event_id % 3 as replica, count(*) as n from {src} group by all"


KEYED_JOIN = "select {keys}, max({v}) as {v} from (({a}) union all ({b})) group by {keys}"
KEYED_DELTA = "select x.* from ({a}) x where not exists (select 1 from ({b}) y where {on} and y.{v} >= x.{v})"
_c = {"a": counter_sql(SQL_A), "b": counter_sql(SQL_B), "v": "n"}
add("growcounter_join", lambda spark, sf: COUNTER.join(*two(spark, sf, counter_state)), KEYED_JOIN.format(keys="user_id, event_type, replica", **_c))
add("growcounter_delta", lambda spark, sf: COUNTER.delta(*two(spark, sf, counter_state)), KEYED_DELTA.format(on="y.user_id = x.user_id and y.event_type = x.event_type and y.replica = x.replica", **_c))

UPDOWN = lattice.up_down_counter("key")
BALANCES = "select {k} % 25 as key, {k} % 2 as replica, case when {v} < 0 then 'neg' else 'pos' end as sign, sum(abs(cast(round({v}*100) as bigint)))::bigint as n from {t} group by all"


def balances(spark, sf, table, k, v):
    c = F.round(F.col(v) * 100).cast("bigint")
    return read(spark, sf, table).groupBy((F.col(k) % 25).alias("key"), (F.col(k) % 2).alias("replica"), F.when(F.col(v) < 0, "neg").otherwise("pos").alias("sign")).agg(F.sum(F.abs(c)).alias("n"))


add("updown_join", lambda spark, sf: UPDOWN.join(balances(spark, sf, "customer", "c_custkey", "c_acctbal"), balances(spark, sf, "supplier", "s_suppkey", "s_acctbal")), KEYED_JOIN.format(keys="key, replica, sign", v="n", a=BALANCES.format(k="c_custkey", v="c_acctbal", t="customer"), b=BALANCES.format(k="s_suppkey", v="s_acctbal", t="supplier")))
MAXREG = lattice.max_register("l_partkey")


def prices(spark, sf, bit):
    return read(spark, sf, "lineitem").where(f"l_orderkey % 2 = {bit}").groupBy("l_partkey").agg(F.max(F.round(F.col("l_extendedprice") * 100).cast("bigint")).alias("v"))


add("maxreg_join", lambda spark, sf: MAXREG.join(prices(spark, sf, 0), prices(spark, sf, 1)), "select l_partkey, max(cast(round(l_extendedprice*100) as bigint)) as v from lineitem group by 1")
LWW = lattice.last_writer_register("user_id", v="value_cents")


def latest(e):
    micros = F.expr(f"timestampdiff(MICROSECOND, {tables.EPOCH}, ts)")
    return LWW.compose(e.select("user_id", micros.alias("ts"), F.col("event_id").alias("tie"), F.round(F.col("value") * 100).cast("bigint").alias("value_cents")))


LATEST = "select user_id, epoch_us(max(ts)) as ts, max_by(event_id, (ts, event_id)) as tie, max_by(cast(round(value*100) as bigint), (ts, event_id)) as value_cents from {src} group by 1"
add("lww_join", lambda spark, sf: LWW.join(*two(spark, sf, latest)), LATEST.format(src=f"(select * from {SQL_A} union select * from {SQL_B})"))
add("lww_delta", lambda spark, sf: LWW.delta(*two(spark, sf, latest)), f"select x.* from ({LATEST.format(src=SQL_A)}) x where not exists (select 1 from ({LATEST.format(src=SQL_B)}) y where y.user_id = x.user_id and (y.ts, y.tie) >= (x.ts, x.tie))")
GROWMAP = lattice.grow_map("k", lattice.grow_set("payload"))
ORD = items_sql("orders")


def order_map(spark, sf, without):
    """Orders but for a third of them: two of these overlap and cover the table."""
    k = F.split_part("payload", F.lit("|"), F.lit(2)).cast("bigint")
    return tables.load_items(spark, sf, "orders").where(F.col("part_key").cast("bigint") % 3 != without).select(k.alias("k"), "payload")


def order_map_sql(without):
    return f"select cast(split_part(payload, '|', 2) as bigint) as k, payload from ({ORD}) where cast(part_key as bigint) % 3 <> {without}"


add("growmap_join", lambda spark, sf: GROWMAP.join(order_map(spark, sf, 0), order_map(spark, sf, 1)), f"{order_map_sql(0)} union {order_map_sql(1)}")
add("growmap_delta", lambda spark, sf: GROWMAP.delta(order_map(spark, sf, 0), order_map(spark, sf, 1)), f"{order_map_sql(0)} except {order_map_sql(1)}")
TWOPHASE = lattice.two_phase_set("doc_id")


def removals(spark, sf, bit):
    flags = read(spark, sf, "labels").select("doc_id", (F.col("toxic") == 1).alias("removed"))
    return flags.where(f"doc_id % 3 != {bit}").withColumn("removed", F.when(F.col("doc_id") % 2 == bit, F.lit(False)).otherwise(F.col("removed")))


def removals_sql(bit):
    return f"select doc_id, case when doc_id % 2 = {bit} then false else toxic = 1 end as removed from labels where doc_id % 3 <> {bit}"


add("twophase_join", lambda spark, sf: TWOPHASE.join(removals(spark, sf, 0), removals(spark, sf, 1)), f"select doc_id, bool_or(removed) as removed from (({removals_sql(0)}) union all ({removals_sql(1)})) group by 1")
ADDWINS = lattice.AddWinsSet()


def dots(e):
    """Per user: purchases, sign-ups, views and clicks add; an error removes what the replica saw of the user before."""
    rows = e.select("user_id", "event_id", "event_type", "ts")
    last_error = rows.where("event_type = 'error'").groupBy("user_id").agg(F.max("event_id").alias("cut"))
    adds = rows.where("event_type != 'error'").join(last_error, "user_id", "left")
    return adds.select(F.col("user_id").alias("elem"), (F.col("event_id") % 3).alias("replica"), F.col("event_id").alias("ctr"), (F.col("cut").isNull() | (F.col("event_id") > F.col("cut"))).alias("live"))


def dots_sql(src):
    return f"select e.user_id as elem, e.event_id % 3 as replica, e.event_id as ctr, (cut is null or e.event_id > cut) as live from {src} e left join (select user_id, max(event_id) as cut from {src} where event_type = 'error' group by 1) c on c.user_id = e.user_id where e.event_type <> 'error'"


add("addwins_join", lambda spark, sf: ADDWINS.join(*two(spark, sf, dots)), f"select elem, replica, ctr, bool_and(live) as live from (({dots_sql(SQL_A)}) union all ({dots_sql(SQL_B)})) group by 1, 2, 3")
add("addwins_delta", lambda spark, sf: ADDWINS.delta(*two(spark, sf, dots)), f"select x.* from ({dots_sql(SQL_A)}) x where not exists (select 1 from ({dots_sql(SQL_B)}) y where y.elem = x.elem and y.replica = x.replica and y.ctr = x.ctr and (not y.live or x.live))")


@query("pair_join", f"select 'left' as side, count(*) as n, sum(total)::bigint as total from (select user_id, sum(n) as total from ({KEYED_JOIN.format(keys='user_id, event_type, replica', **_c)}) group by 1) union all select 'right', count(*), sum(v)::bigint from (select user_id, max(v) as v from (select user_id, cast(round(value*100) as bigint) as v from {SQL_A} union all select user_id, cast(round(value*100) as bigint) from {SQL_B}) group by 1)")
def pair_join(spark, sf):
    high = lattice.max_register("user_id")
    both = lattice.PairLattice(COUNTER, high)
    a, b = two(spark, sf, lambda e: (counter_state(e), e.groupBy("user_id").agg(F.max(F.round(F.col("value") * 100).cast("bigint")).alias("v"))))
    left, right = both.join(a, b)
    rows = left.groupBy("user_id").agg(F.sum("n").alias("total")).agg(F.lit("left").alias("side"), F.count("*").alias("n"), F.sum("total").alias("total"))
    return rows.unionByName(right.agg(F.lit("right").alias("side"), F.count("*").alias("n"), F.sum("v").alias("total")))


NESTED = lattice.grow_map("k1", lattice.grow_map("k2", lattice.max_register(v="shipped")))


def shipments(spark, sf, bit):
    o, li = read(spark, sf, "orders"), read(spark, sf, "lineitem").where(f"l_linenumber % 2 = {bit}")
    return o.join(li, o.o_orderkey == li.l_orderkey).groupBy(F.col("o_custkey").alias("k1"), F.col("o_orderkey").alias("k2")).agg(F.max(F.date_format("l_shipdate", "yyyy-MM-dd")).alias("shipped"))


add("nested_map_join", lambda spark, sf: NESTED.join(shipments(spark, sf, 0), shipments(spark, sf, 1)), "select o_custkey as k1, o_orderkey as k2, max(strftime(l_shipdate, '%Y-%m-%d')) as shipped from orders join lineitem on l_orderkey = o_orderkey group by 1, 2")


@query("lattice_over_protocol", KEYED_JOIN.format(keys="user_id, event_type, replica", **_c))
def lattice_over_protocol(spark, sf):
    """A counter synchronised part by part: entries that differ travel, the join keeps the greater."""
    a, b = two(spark, sf, counter_state)
    result = PROTOCOLS["rateless"](Replicas.single(snapshot(COUNTER.parts(a)), snapshot(COUNTER.parts(b))))
    return COUNTER.from_parts(result.state_a, "user_id bigint, event_type string, replica bigint, n bigint")


# ---- pairs ----
def pair_sql(table: str, s: float) -> str:
    return (
        f"select payload, nbytes, h, d, d2, case when rank <= sh then 'both' when rank <= c then 'a' else 'b' end as side from (select *, cast(round(2*{s}*c/(1+{s})) as bigint) as sh from "
        f"(select *, row_number() over (order by h) as rank, (count(*) over ()) // 2 as c from ({digests_sql(f'select distinct payload from ({items_sql(table)})')}))) where rank <= 2*c - sh"
    )


def pair_of(spark, sf, table: str, s: float) -> DataFrame:
    return replicas.make_pair(tables.parts_of(spark, sf, table), s)


for _s in (0.0, 0.25, 0.5, 0.75, 1.0):
    add(f"pair_exact_s{round(_s * 100):02d}", lambda spark, sf, s=_s: pair_of(spark, sf, "events", s).select("payload", "h", "side"), f"select payload, h, side from ({pair_sql('events', _s)})")
add("pair_exact_lineitem_s75", lambda spark, sf: pair_of(spark, sf, "lineitem", 0.75).groupBy("side").agg(F.count("*").alias("n"), F.sum("nbytes").alias("nbytes")), f"select side, count(*) as n, sum(nbytes)::bigint as nbytes from ({pair_sql('lineitem', 0.75)}) group by 1")
add("pair_threshold_s50", lambda spark, sf: replicas.make_pair(tables.parts_of(spark, sf, "events"), 0.5, mode="threshold").select("h", "side"), f"select h, case when d / {float(1 << 60)!r} < 0.5 then 'both' when d2 % 2 = 0 then 'a' else 'b' end as side from ({digests_sql(EV)})")


@query("jaccard_by_similarity", " union all ".join(f"select {s}::double as s, count(*) filter (side = 'both') as shared, count(*) as either from ({pair_sql('events', s)})" for s in (0.0, 0.5, 0.75, 1.0)))
def jaccard_by_similarity(spark, sf):
    out = None
    for s in (0.0, 0.5, 0.75, 1.0):
        row = replicas.jaccard(*replicas.sides(pair_of(spark, sf, "events", s))).select(F.lit(s).alias("s"), "shared", "either")
        out = row if out is None else out.unionByName(row)
    return out


add("uniform_strings", lambda spark, sf: replicas.uniform_strings(tables.load_items(spark, sf, "lineitem"), 20, 64), f"select substr(concat(h, sha256(payload), sha256(payload || '+')), 1, cast(20 + d % 45 as int)) as payload from ({digests_sql(items_sql('lineitem'))})")
add("natural_split_events", lambda spark, sf: replicas.natural_events(spark, sf).groupBy("side").agg(F.count("*").alias("n")), "select case when ts < timestamp '2024-01-21' and ts >= timestamp '2024-01-11' then 'both' when ts < timestamp '2024-01-21' then 'a' else 'b' end as side, count(*) as n from events group by 1")
add("natural_split_documents", lambda spark, sf: replicas.natural_documents(spark, sf).groupBy("side").agg(F.count("*").alias("n")), "select side, count(*) as n from (select text, case when min(o) <> max(o) then 'both' when min(o) = 0 then 'a' else 'b' end as side from (select text, cast(regexp_extract(source, '(\\d+)$', 1) as int) % 2 as o from documents) group by 1) group by 1")

# ---- protocols on one pair: events at s = 0.75, buckets at one per part, filters at 1 % ----
S, EPS, LOAD = 0.75, 0.01, 1.0
WIRE = SyncConfig().wire


def replicas_of(spark, sf, table="events", s=S, eps=EPS, load_factor=LOAD, segments=None) -> Replicas:
    pair = snapshot(pair_of(spark, sf, table, s), "pair")
    return Replicas.single(*replicas.sides(pair), SyncConfig(eps=eps, load_factor=load_factor, segments=segments))


def run(spark, sf, protocol: str, segments: int | None = None, **options) -> SyncResult:
    return PROTOCOLS[protocol](replicas_of(spark, sf, segments=segments, **options), SyncConfig(segments=segments))


def filter_sql(name: str, members: str, eps: float) -> str:
    """CTEs of a filter over members (d, d2): its shape and its set bits."""
    return (
        f"{name}_shape as (select greatest(cast(ceil(-count(*)*ln({eps}::double)/{LN2**2!r}) as bigint), 1) as m, greatest(cast(round(-ln({eps}::double)/{LN2!r}) as int), 1) as k from {members}), "
        f"{name} as (select distinct (d % m + i * (d2 % m)) % m as p from {members}, {name}_shape, range(64) t(i) where i < k)"
    )


def split_ctes(table="events", s=S, eps=EPS) -> str:
    return (
        f"with p as ({pair_sql(table, s)}), a as (select * from p where side in ('both', 'a')), b as (select * from p where side in ('both', 'b')), "
        f"{filter_sql('fa', 'a', eps)}, {fast_probe('com_b', 'b', 'fa')}, excl_b as (select * from b where h not in (select h from com_b)), "
        f"{filter_sql('fb', 'com_b', eps)}, {fast_probe('com_a', 'a', 'fb')}, excl_a as (select * from a where h not in (select h from com_a))"
    )


def fast_probe(name: str, probes: str, f: str) -> str:
    """The same as a join: members whose k positions are all set bits."""
    return f"{name} as (select * from {probes} where h in (select h from (select x.h, (x.d % s.m + i * (x.d2 % s.m)) % s.m as q, s.k as k from {probes} x, {f}_shape s, range(64) t(i) where i < s.k) z join {f} on {f}.p = z.q group by h, k having count(*) = k))"


AB = f"with p as ({pair_sql('events', S)}), a as (select * from p where side in ('both', 'a')), b as (select * from p where side in ('both', 'b'))"
BOTH_FINAL = "select 'a' as side, payload from p union all select 'b', payload from p"


def final(protocol: str, segments: int | None = None, **options):
    return lambda spark, sf: run(spark, sf, protocol, segments, **options).states().drop("sid")


def final_sql(table="events", s=S) -> str:
    return f"with p as ({pair_sql(table, s)}) {BOTH_FINAL}"


for _p in PROTOCOLS:
    if _p != "filter_only":
        add(f"{_p}_final", final(_p), final_sql())
add("rateless_final_segments", final("rateless", 16), final_sql())
add("filter_rateless_final_segments", final("filter_rateless", 16), final_sql())
add("filter_rateless_final_documents", final("filter_rateless", table="documents", s=0.5), final_sql("documents", 0.5))
add("rateless_final_disjoint", final("rateless", s=0.0), final_sql(s=0.0))
add("rateless_final_equal", final("rateless", s=1.0), final_sql(s=1.0))


def transcript(protocol: str, **options):
    return lambda spark, sf: run(spark, sf, protocol, **options).transcript.drop("sid", "protocol")


def message(seq: int, sender: str, kind: str, metadata: str = "0", payload: str | None = None, receiver: str | None = None) -> str:
    """One transcript row in SQL: payload and receiver are relations with nbytes and h."""
    total = f"(select coalesce(sum(nbytes), 0)::bigint from {payload})" if payload else "0"
    again = f"(select coalesce(sum(nbytes), 0)::bigint from {payload} where h in (select h from {receiver}))" if payload and receiver else "0"
    items = f"(select count(*) from {payload})" if payload else "0"
    return f"select {seq} as seq, '{sender}' as sender, '{kind}' as kind, ({metadata})::bigint as metadata_bytes, {total} as payload_bytes, {again} as redundant_bytes, {items} as n_items"


def messages(*rows: str) -> str:
    return " union all ".join(rows)


B_ONLY, A_ONLY = "(select * from b where h not in (select h from a))", "(select * from a where h not in (select h from b))"
add("state_driven_transcript", transcript("state_driven"), f"{AB} {messages(message(1, 'A', 'sync', payload='a', receiver='b'), message(2, 'B', 'missing_state', payload=B_ONLY, receiver='a'))}")
add("full_exchange", lambda spark, sf: deltas.full_exchange(replicas_of(spark, sf)).transcript.drop("sid", "protocol"), f"{AB} {messages(message(1, 'A', 'state', payload='a', receiver='b'), message(2, 'B', 'state', payload='b', receiver='a'))}")


def bucket_ctes(a: str, b: str, count_of: str, load: float) -> str:
    digest = "md5(bucket || ':' || string_agg(h, '' order by h))"
    return (
        f"nb as (select greatest(cast(floor(count(*) * {load}) as bigint), 1) as n from {count_of}), ax as (select *, d % n as bucket from {a}, nb), bx as (select *, d % n as bucket from {b}, nb), "
        f"da as (select bucket, count(*) as n_parts, sum(nbytes)::bigint as nbytes, {digest} as digest from ax group by bucket), db as (select bucket, {digest} as digest from bx group by bucket), "
        "bad as (select coalesce(da.bucket, db.bucket) as bucket from da full join db on da.bucket = db.bucket where da.digest is distinct from db.digest), "
        "whole_a as (select * from ax where bucket in (select bucket from bad)), whole_b as (select * from bx where bucket in (select bucket from bad))"
    )


def plain_buckets(load: float = LOAD, s: float = S) -> str:
    return f"with p as ({pair_sql('events', s)}), a as (select * from p where side in ('both', 'a')), b as (select * from p where side in ('both', 'b')), {bucket_ctes('a', 'b', 'a', load)}"


REST_A = "(select * from whole_a where h not in (select h from whole_b))"
REST_B = "(select * from whole_b where h not in (select h from whole_a))"
add("bucketed_transcript", transcript("bucketed"), f"{plain_buckets()} {messages(message(1, 'A', 'bucket_digests', f'(select n * {WIRE.digest} from nb)'), message(2, 'B', 'buckets', f'(select count(*) * {WIRE.bucket_index} from bad)', 'whole_b', 'a'), message(3, 'A', 'missing_state', payload=REST_A, receiver='b'))}")


def bucketed_side(spark, sf, load):
    r = replicas_of(spark, sf, load_factor=load)
    return numbered(r.a, counts_by(r.a, r.sessions))


for _n, _f in (("f02", 0.2), ("f1", 1.0), ("f5", 5.0)):
    add(f"bucket_sizes_{_n}", lambda spark, sf, f=_f: bucketed_side(spark, sf, f).groupBy("bucket").agg(F.count("*").alias("n_parts")), f"{plain_buckets(_f)} select bucket, n_parts from da")
add("bucket_digests", lambda spark, sf: buckets.bucket_digests(bucketed_side(spark, sf, LOAD)).drop("sid"), f"{plain_buckets()} select bucket, n_parts, nbytes, digest from da")
add("bucket_digests_xor", lambda spark, sf: buckets.bucket_digests(bucketed_side(spark, sf, LOAD), "xor").select("bucket", "digest"), f"{plain_buckets()} select bucket, md5(concat_ws(':', bucket, bit_xor(d), bit_xor(d2), count(*))) as digest from ax group by bucket")
add("bucket_mismatch", lambda spark, sf: run(spark, sf, "bucketed").details.select("bucket"), f"{plain_buckets()} select bucket from bad")
add("bucketed_rateless_mismatch", lambda spark, sf: run(spark, sf, "bucketed_rateless").details.select("bucket"), f"{plain_buckets()} select bucket from bad")


def redundancy_sql(protocol: str, loads=(0.2, 1.0, 5.0), similarities=(0.25, 0.75)) -> str:
    rows = [f"select {s}::double as s, {f}::double as load_factor, (select coalesce(sum(nbytes), 0)::bigint from whole_b where h in (select h from a)) as redundant_bytes from nb" for s in similarities for f in loads]
    return " union all ".join(f"select * from ({plain_buckets(f, s)} {row})" for row, (s, f) in zip(rows, [(s, f) for s in similarities for f in loads]))


for _p in ("bucketed", "bucketed_rateless"):
    add(f"{_p}_redundancy", lambda spark, sf, p=_p: workloads.sweep(tables.parts_of(spark, sf, "events"), [p], [0.25, 0.75], load_factors=[0.2, 1.0, 5.0]).select("s", "load_factor", "redundant_bytes"), redundancy_sql(_p))


@query("ten_bucket_case", "select 100 as sent, 10 as needed, 10::double as overhead")
def ten_bucket_case(spark, sf):
    """Ten buckets of nine shared parts and one new part each: all hundred travel for ten."""
    rows = tables.parts_of(spark, sf, "orders").orderBy("h").limit(100).select("h", "nbytes", F.row_number().over(replicas.Window.orderBy("h")).alias("i"))
    placed = rows.select("h", "nbytes", F.lit(0).cast("bigint").alias("sid"), (F.col("i") % 10).alias("bucket"), (F.col("i") <= 10).alias("new")).withColumn("d", F.col("bucket"))
    bad = buckets.mismatched(buckets.bucket_digests(placed), buckets.bucket_digests(placed.where("not new")))
    sent = placed.join(bad, ["sid", "bucket"], "left_semi")
    return sent.agg(F.count("*").alias("sent"), F.count_if("new").alias("needed")).withColumn("overhead", F.col("sent") / F.col("needed"))


# ---- filters ----
add("filter_words", lambda spark, sf: (lambda r: membership.filter_words(r.a, membership.shaped(r.a, r.sessions)).select("word", "bits"))(replicas_of(spark, sf)), f"{AB}, {filter_sql('fa', 'a', EPS)} select cast(p // 32 as int) as word, bit_or(1::bigint << (p % 32)::int)::bigint as bits from fa group by 1")
add("filter_split_b", lambda spark, sf: (lambda s: s.com_b.select("h", F.lit("common").alias("part")).unionByName(s.excl_b.select("h", F.lit("exclusive").alias("part"))))(filter_split(replicas_of(spark, sf))), f"{split_ctes()} select h, 'common' as part from com_b union all select h, 'exclusive' from excl_b")
add("filter_split_a", lambda spark, sf: (lambda s: s.com_a.select("h", F.lit("common").alias("part")).unionByName(s.excl_a.select("h", F.lit("exclusive").alias("part"))))(filter_split(replicas_of(spark, sf))), f"{split_ctes()} select h, 'common' as part from com_a union all select h, 'exclusive' from excl_a")


@query("filter_fpr_8bits", f"with a as ({digests_sql(EV)}), b as ({digests_sql(ORD)}), fa_shape as (select count(*) * 8 as m, 5 as k from a), fa as (select distinct (d % m + i * (d2 % m)) % m as p from a, fa_shape, range(5) t(i)), {fast_probe('com_b', 'b', 'fa')} select (select count(*) from b) as tested, (select count(*) from com_b) as hits")
def filter_fpr_8bits(spark, sf):
    """Eight bits a part and five hashes: about 2.2 % of strangers pass."""

    def keyed(table: str) -> DataFrame:
        parts = snapshot(keyed_parts(spark, sf, table), "parts")
        return parts.withColumn("seg", segment_of(segments_for(parts.count())))

    members = keyed("events")
    settings = spark.range(1).select(F.col("id").alias("sid"), F.lit(0.01).alias("eps"))
    return membership.measured_fpr(membership.build_filter(members, settings, 8, 5), keyed("orders"), members).select("tested", "hits")


HIDDEN = "select h, 'a' as lacks from com_b where h not in (select h from a) union all select h, 'b' from com_a where h not in (select h from b)"
add("filter_only_residual", lambda spark, sf: run(spark, sf, "filter_only").details.select("h", "lacks"), f"{split_ctes()} {HIDDEN}")
BYTES_A, BYTES_B = "(select cast(ceil(m / 8.0) as bigint) from fa_shape)", "(select cast(ceil(m / 8.0) as bigint) from fb_shape)"
add("filter_only_transcript", transcript("filter_only"), f"{split_ctes()} {messages(message(1, 'A', 'filter', BYTES_A), message(2, 'B', 'filter_and_exclusive', BYTES_B, 'excl_b', 'a'), message(3, 'A', 'exclusive', payload='excl_a', receiver='b'))}")
FB_CTES = f"{split_ctes()}, {bucket_ctes('com_a', 'com_b', 'com_b', LOAD)}"
add("filter_bucketed_transcript", transcript("filter_bucketed"), f"{FB_CTES} {messages(message(1, 'A', 'filter', BYTES_A), message(2, 'B', 'filter_exclusive_digests', f'{BYTES_B} + (select n * {WIRE.digest} from nb)', 'excl_b', 'a'), message(3, 'A', 'exclusive_and_buckets', f'(select count(*) * {WIRE.bucket_index} from bad)', '(select nbytes, h from excl_a union all select nbytes, h from whole_a)', 'b'), message(4, 'B', 'missing_state', payload=REST_B, receiver='a'))}")

# ---- coded cells ----
WALK_SQL = (
    "with recursive p as ({src}), walk as (select h, d, d2, 0::bigint as i, 1 as n from p union all "
    "select h, d, d2, i + greatest(1, cast(ceil((i + 1.5) * (1.0::double / sqrt(1.0 - ('0x'||substr(md5(h || '#' || n),1,13))::bigint::double / 4503599627370496.0) - 1.0)) as bigint)), n + 1 from walk where i < {upto}), c as (select * from walk where i < {upto}) "
)


def cells_sql(src: str, upto: int) -> str:
    return WALK_SQL.format(src=src, upto=upto)


def keyed_parts(spark, sf, table):
    return tables.parts_of(spark, sf, table).withColumn("sid", F.lit(0).cast("bigint"))


add("cell_indices", lambda spark, sf: keyed_parts(spark, sf, "supplier").select("h", F.explode(coded.md5_indices(F.col("h"), 500)).alias("i")).withColumn("i", F.col("i").cast("bigint")), f"{cells_sql(digests_sql(items_sql('supplier')), 500)} select h, i from c")
CELL_SELECT = "select cast(i as int) as i, bit_xor(d) as id_sum, bit_xor(d2) as check_sum, count(*) as cnt from c group by i"
add("coded_cells_prefix", lambda spark, sf: coded.md5_cells(keyed_parts(spark, sf, "orders"), 200).drop("sid", "seg"), f"{cells_sql(digests_sql(ORD), 200)} {CELL_SELECT}")


def pair_parts(spark, sf):
    """Both sides in one segment: one row a cell, however large the table is."""
    r = replicas_of(spark, sf, segments=1)
    return r.a, r.b


add("cell_subtract", lambda spark, sf: (lambda a, b: coded.subtract_cells(coded.md5_cells(a, 128), coded.md5_cells(b, 128)).where("id_sum != 0 or cnt != 0").drop("sid", "seg"))(*pair_parts(spark, sf)), f"{cells_sql(pair_sql('events', S), 128).replace('select h, d, d2, 0::bigint', 'select h, d, d2, side, 0::bigint').replace('select h, d, d2, i +', 'select h, d, d2, side, i +')} select cast(i as int) as i, bit_xor(d) as id_sum, bit_xor(d2) as check_sum, sum(case side when 'a' then 1 else -1 end)::bigint as cnt from c where side <> 'both' group by i")


@query("cell_prefix_consistency", "select true as same, 64 as cells")
def cell_prefix_consistency(spark, sf):
    """The first cells of a longer stream are the cells of a shorter one, for both walks."""
    parts, some = keyed_parts(spark, sf, "orders"), keyed_parts(spark, sf, "customer")
    short, full = coded.coded_cells(parts, 0, 64), coded.coded_cells(parts, 0, 256).where("i < 64")
    other = coded.md5_cells(some, 256).where("i < 64").exceptAll(coded.md5_cells(some, 64)).count()
    return spark.createDataFrame([(short.exceptAll(full).isEmpty() and full.exceptAll(short).isEmpty() and other == 0, short.count())], "same boolean, cells int")


DIFFERENCE = "select h, case side when 'a' then 'a_only' else 'b_only' end as owner from p where side <> 'both'"
add("rateless_difference", lambda spark, sf: (lambda r: reconcile(digests_of(r.a), digests_of(r.b), SyncConfig()).rows.join(r.a.unionByName(r.b).select("d", "h").distinct(), "d").select("h", "owner"))(replicas_of(spark, sf)), f"{AB} {DIFFERENCE}")
add("rateless_payload", lambda spark, sf: run(spark, sf, "rateless").transcript.where("kind != 'cells'").drop("sid", "protocol"), f"{AB} {messages(message(2, 'B', 'end_of_stream', f'(select count(*) * {WIRE.digest} from {A_ONLY})', B_ONLY, 'a'), message(3, 'A', 'missing_state', payload=A_ONLY, receiver='b'))}")
add("rateless_transcript", transcript("rateless"))
add("filter_rateless_transcript", transcript("filter_rateless"))
add("bucketed_rateless_transcript", transcript("bucketed_rateless"))
add("filter_bucketed_rateless_transcript", transcript("filter_bucketed_rateless"))
add("filter_rateless_false_positives", lambda spark, sf: (lambda r: run(spark, sf, "filter_rateless").details.join(r.a.unionByName(r.b).select("d", "h").distinct(), "d").select("h", F.when(F.col("owner") == "a_only", "b").otherwise("a").alias("lacks")))(replicas_of(spark, sf)), f"{split_ctes()} {HIDDEN}")
HIDDEN_A, HIDDEN_B = "(select nbytes, h from com_a where h not in (select h from com_b))", "(select nbytes, h from com_b where h not in (select h from com_a))"
add("filter_rateless_payload", lambda spark, sf: run(spark, sf, "filter_rateless").transcript.where("kind != 'cells'").drop("sid", "protocol"), f"{split_ctes()} {messages(message(1, 'A', 'filter', BYTES_A), message(2, 'B', 'init_stream', BYTES_B, 'excl_b', 'a'), message(4, 'A', 'end_of_stream', f'(select count(*) * {WIRE.digest} from {HIDDEN_B})', f'(select nbytes, h from excl_a union all select * from {HIDDEN_A})', 'b'), message(5, 'B', 'missing_hidden', payload=HIDDEN_B, receiver='a'))}")


@query("cells_per_difference")
def cells_per_difference(spark, sf):
    """Cells used for differences of d parts, several sets of each size: one session each."""
    parts = snapshot(tables.parts_of(spark, sf, "events").select("h", "d", "d2"), "parts")
    most = parts.count()
    trials = [(i, min(d, most)) for i, d in enumerate([1] * 8 + [2] * 8 + [5] * 8 + [10] * 8 + [50] * 4 + [200] * 2 + [400, 1000, 5000])]
    table = spark.createDataFrame(trials, "sid bigint, size int")
    rank = F.row_number().over(replicas.Window.partitionBy("sid").orderBy(F.md5(F.concat("h", F.col("sid").cast("string")))))
    chosen = parts.crossJoin(F.broadcast(table)).withColumn("r", rank).where("r <= size").select("sid", F.lit(0).alias("seg"), "d", "d2")
    used = reconcile(chosen, chosen.limit(0), SyncConfig()).used
    return used.join(table, "sid").groupBy("size").agg(F.avg(ratio := F.col("cells") / F.col("size")).alias("cells_per_part"), F.percentile(ratio, 0.99).alias("cells_per_part_p99"), F.count("*").alias("trials"))


@query("peel_rounds_dataframe", "with p as (" + pair_sql("supplier", 0.75) + ") " + "select h, case side when 'a' then 'a_only' else 'b_only' end as owner from p where side <> 'both'")
def peel_rounds_dataframe(spark, sf):
    """The decoder as joins, over cells of the portable walk."""
    r = replicas_of(spark, sf, "supplier")
    members = r.a.unionByName(r.b)
    return coded.difference_by_joins(r.a, r.b).join(members.select("d", "h").distinct(), "d").select("h", "owner")


# ---- related techniques ----
@query("delta_shipping_after_gap", "with l as (select event_id as seq, octet_length(encode(payload)) as nbytes from events join (" + EV + ") on part_key = cast(event_id as varchar)), k as (select 'near' as peer, (select max(seq) - 50 from l) as acked union all select 'gone', 10) select peer, case when acked + 1 < (select max(seq) - 500 from l) then 'full' else 'delta' end as mode, count(seq) as n_items, coalesce(sum(nbytes), 0)::bigint as nbytes from k left join l on acked + 1 < (select max(seq) - 500 from l) or seq > acked group by peer, mode")
def delta_shipping_after_gap(spark, sf):
    log = tables.load_items(spark, sf, "events").select(F.col("part_key").cast("bigint").alias("seq"), "nbytes")
    top = log.agg(F.max("seq")).first()[0]
    acks = spark.createDataFrame([("near", top - 50), ("gone", 10)], "peer string, acked bigint")
    return deltas.delta_shipping(log, acks, top - 500)


@query("clock_delta", "select event_id % 3 as replica, event_id as ctr from events e where event_id > coalesce((select max(event_id) from events x where x.ts < timestamp '2024-01-11' and x.event_id % 3 = e.event_id % 3), -1)")
def clock_delta(spark, sf):
    e = read(spark, sf, "events")
    state = e.select((F.col("event_id") % 3).alias("replica"), F.col("event_id").alias("ctr"))
    old = e.where(F.col("ts").cast("timestamp_ntz") < F.expr("timestamp_ntz'2024-01-11 00:00:00'")).select((F.col("event_id") % 3).alias("replica"), F.col("event_id").alias("ctr"))
    return deltas.clock_delta(state, deltas.version_vector(old))


@query("fixed_table_cells", f"with p as ({digests_sql(ORD)}) select cast(j * 64 + (d % (1000003 + 2*j) + d2 % (999983 - 2*j)) % 64 as int) as i, bit_xor(d) as id_sum, bit_xor(d2) as check_sum, count(*) as cnt from p, range(4) t(j) group by 1")
def fixed_table_cells(spark, sf):
    return fixed_table.table_cells(keyed_parts(spark, sf, "orders"), 256).drop("sid", "seg")


add("fixed_table_restarts", lambda spark, sf: (lambda r: (lambda found, attempts: found.rows.groupBy("owner").agg(F.count("*").alias("n")).withColumn("attempts", F.lit(attempts)).crossJoin(found.used.agg(F.sum("cells").alias("cells_sent"))))(*fixed_table.with_restarts(digests_of(r.a), digests_of(r.b), 64)))(replicas_of(spark, sf)))
add("fixed_table_final", lambda spark, sf: fixed_table.fixed_table_reconcile(replicas_of(spark, sf), 256).states().drop("sid"), final_sql())
add("filter_fixed_table_failures", lambda spark, sf: fixed_table.failure_rate(replicas_of(spark, sf, segments=32), [0.5, 1.0, 2.0, 4.0]))
add("filter_fixed_table", lambda spark, sf: fixed_table.filter_fixed_table(replicas_of(spark, sf)))
for _h in ("bottom_k", "theta", "strata"):
    add(f"estimate_{_h}", lambda spark, sf, h=_h: (lambda r: estimators.estimate_difference(r.a, r.b, h))(replicas_of(spark, sf)))
TREE_LEVEL = "select {l} as level, count(*) as compared, count(*) filter (x is distinct from y) as differing from (select prefix, a.v as x, b.v as y from (select substr(h,1,{l}) as prefix, (bit_xor(d), bit_xor(d2), count(*)) as v from a group by 1) a full join (select substr(h,1,{l}) as prefix, (bit_xor(d), bit_xor(d2), count(*)) as v from b group by 1) b using (prefix))"
add("tree_sync_levels", lambda spark, sf: (lambda r: tree.tree_sync(r.a, r.b, 2)[0])(replicas_of(spark, sf)), f"{AB} {TREE_LEVEL.format(l=1)} union all select 2, count(*), count(*) filter (x is distinct from y) from (select prefix, a.v as x, b.v as y from (select substr(h,1,2) as prefix, (bit_xor(d), bit_xor(d2), count(*)) as v from a group by 1) a full join (select substr(h,1,2) as prefix, (bit_xor(d), bit_xor(d2), count(*)) as v from b group by 1) b using (prefix)) where substr(prefix, 1, 1) in (select prefix from (select prefix, a.v as x, b.v as y from (select substr(h,1,1) as prefix, (bit_xor(d), bit_xor(d2), count(*)) as v from a group by 1) a full join (select substr(h,1,1) as prefix, (bit_xor(d), bit_xor(d2), count(*)) as v from b group by 1) b using (prefix)) where x is distinct from y)")


def shifted_files(spark, sf):
    files = read(spark, sf, "benchmark").select(F.col("item_id").alias("id"), "text")
    return files.withColumn("text", F.concat(F.lit("+"), "text")), files


FILES = "with s as (select item_id as id, text from benchmark), p as (select id, '+' || text as text from s)"
add("block_sync_documents", lambda spark, sf: blocks.block_sync(*shifted_files(spark, sf), 32))
add("fixed_block_diff", lambda spark, sf: blocks.fixed_block_diff(*shifted_files(spark, sf), 32), f"{FILES}, pb as (select id, o as off, substr(text, cast(o + 1 as int), 32) as x from p, range(0, 100000, 32) t(o) where o < length(text)), sb as (select id, o as off, substr(text, cast(o + 1 as int), 32) as y from s, range(0, 100000, 32) t(o) where o < length(text)) select id, count(*) as blocks, sum(case when x is not distinct from y then 0 else length(x) end)::bigint as literal_chars from pb left join sb using (id, off) group by 1")
add("every_offset_diff", lambda spark, sf: blocks.every_offset_diff(*shifted_files(spark, sf), 32), f"{FILES}, w as (select id, o as off, substr(text, cast(o + 1 as int), 32) as x from p, range(0, 4000) t(o) where o <= length(text) - 32), sb as (select id, min(o) as from_off, substr(text, cast(o + 1 as int), 32) as y from s, range(0, 4000, 32) t(o) where o < length(text) and length(substr(text, cast(o + 1 as int), 32)) = 32 group by 1, 3) select w.id, cast(off as int) as off, cast(from_off as int) as from_off from w join sb on sb.id = w.id and x = y")

# ---- cost model, for replicas of events as large as the table makes them ----
GRID_S = [0.0, 0.05, 0.25, 0.45, 0.5, 0.75, 0.9, 0.93, 0.95, 0.99, 1.0]
MEASURED_SQL = f"select (count(*) // 2)::double as c, coalesce(avg(octet_length(encode(payload))), 0)::double as mbar from ({EV})"
PREDICT_SQL = (
    f"with m as ({MEASURED_SQL}), g as (select s::double as s, eps::double as eps, f::double as f, c, mbar from m, (values " + ", ".join(f"({s})" for s in GRID_S) + ") a(s), (values (0.001), (0.01), (0.05), (0.25)) b(eps), (values (0.2), (1.0), (5.0)) d(f)), "
    f"h as (select *, 2*s*c/(1+s) as n, c - 2*s*c/(1+s) as e, -ln(eps)/{costmodel.FILTER_DIVISOR!r} as beta from g) "
    f"select s, eps, f as load_factor, round(n*mbar + 2*e*mbar, 3) as state_driven, round(1.35*2*e*{WIRE.cell} + e*{WIRE.digest} + 2*e*mbar, 3) as rateless, round(beta*(c + n + eps*e) + 1.35*2*eps*e*{WIRE.cell} + eps*e*{WIRE.digest} + 2*e*mbar, 3) as filter_rateless from h"
)


def grid_of_events(spark, sf, *parameters: list[float]) -> DataFrame:
    return costmodel.combined(costmodel.measured(tables.load_items(spark, sf, "events")), *parameters)


@query("predict_grid", PREDICT_SQL)
def predict_grid(spark, sf):
    rows = costmodel.predicted(grid_of_events(spark, sf, GRID_S, [0.001, 0.01, 0.05, 0.25], [0.2, 1.0, 5.0]))
    return rows.select("s", "eps", "load_factor", *[F.round(p, 3).alias(p) for p in ("state_driven", "rateless", "filter_rateless")])


@query("best_protocol_by_similarity", f"select s, case when state_driven <= least(rateless, filter_rateless) then 'state_driven' when rateless <= filter_rateless then 'rateless' else 'filter_rateless' end as best from ({PREDICT_SQL}) where eps = 0.01 and load_factor = 1.0")
def best_protocol_by_similarity(spark, sf):
    rows = costmodel.predicted(grid_of_events(spark, sf, GRID_S, [0.01], [1.0]))
    three = ("state_driven", "rateless", "filter_rateless")
    least = F.least(*[F.round(p, 3) for p in three])
    best = F.when(F.round(F.col(three[0]), 3) <= least, three[0]).when(F.round(F.col(three[1]), 3) <= least, three[1]).otherwise(three[2])
    return rows.select("s", best.alias("best"))


@query("optimal_eps", "select s, round(case when c - n <= 0 then 1 else least(1, (c + n) / (" + repr(costmodel.FILTER_DIVISOR) + f" * (c - n) * (2*1.35*{WIRE.cell} + {WIRE.digest}))) end, 9) as eps from (select s::double as s, c, 2*s*c/(1+s)::double as n from ({MEASURED_SQL}), (values " + ", ".join(f"({s}::double)" for s in GRID_S) + ") a(s))")
def optimal_eps(spark, sf):
    rows = grid_of_events(spark, sf, GRID_S, [0.01], [1.0])
    return rows.select("s", F.round(costmodel.optimal_eps_of(F.col("s"), F.col("c")), 9).alias("eps"))


@query("crossover_points")
def crossover_points(spark, sf):
    """Where the predicted order of two protocols changes, on a grid of hundredths."""
    rows = costmodel.predicted(grid_of_events(spark, sf, [k / 100 for k in range(101)], [0.01], [1.0]))
    long = rows.select("s", F.explode(F.create_map(*[x for p in ("state_driven", "rateless", "filter_rateless") for x in (F.lit(p), F.col(p))])).alias("protocol", "total_bytes"))
    out = None
    for a, b in (("state_driven", "rateless"), ("rateless", "filter_rateless"), ("state_driven", "filter_rateless")):
        found = crossover(long, a, b)
        out = found if out is None else out.unionByName(found)
    return out


# ---- several peers ----
def peers_of(spark, sf):
    """One replica per source of documents; rows without a source are a replica of their own."""
    d = read(spark, sf, "documents").select(F.coalesce("source", F.lit("")).alias("peer"), F.coalesce("text", F.lit("")).alias("payload")).distinct()
    return with_digest(d.withColumn("nbytes", F.octet_length("payload")))


def cube(names: list[str]) -> dict[str, list[str]]:
    """Edges between names whose places differ by one bit: a graph of logarithmic width, if need be without its last corners."""
    return {a: [names[i ^ 1 << k] for k in range(len(names).bit_length()) if i < i ^ 1 << k < len(names)] for i, a in enumerate(names)}


def gossiped(spark, sf, how: str):
    peers = peers_of(spark, sf)
    topology = cube(gossip.names_of(peers)) if how == "topology" else None
    return gossip.gossip(peers, how, "filter_rateless" if how == "similarity" else "state_driven", topology=topology, payloads=False)[0].select("peer", "h")


def star(spark, sf):
    peers = snapshot(peers_of(spark, sf), "peers")
    center = gossip.names_of(peers)[0]
    return gossip.sync_many(peers.where(F.col("peer") == center).drop("peer"), peers.where(F.col("peer") != center))[0].select("h")


ALL_PEERS = "with d as (select distinct coalesce(source, '') as source, coalesce(text, '') as text from documents) select s.source as peer, md5(t.text) as h from (select distinct source from d) s, (select distinct text from d) t"
for _h in ("random", "ring", "similarity", "topology"):
    add(f"gossip_{_h}", lambda spark, sf, h=_h: gossiped(spark, sf, h), ALL_PEERS)
add("sync_many_star", star, "select distinct md5(coalesce(text, '')) as h from documents")

# ---- workloads ----
FEW = [0.0, 0.25, 0.5, 0.75, 0.95, 1.0]


def events_parts(spark, sf):
    return tables.parts_of(spark, sf, "events")


add("w1_no_filter", lambda spark, sf: workloads.without_filters(events_parts(spark, sf), similarities=FEW, load_factors=[0.2, 5.0]))
add("w2_filter", lambda spark, sf: workloads.with_filters(events_parts(spark, sf), similarities=FEW, eps=[0.01, 0.25], load_factors=[0.2]))
add("w3_high_similarity", lambda spark, sf: workloads.high_similarity(events_parts(spark, sf), eps=[0.01, 0.25]))
add("w4_best_four", lambda spark, sf: workloads.best_four(events_parts(spark, sf), FEW))
add("w5_filter_ablation", lambda spark, sf: workloads.filter_ablation(events_parts(spark, sf), [0.0, 0.5, 0.95]))
add("w6_bucket_ablation", lambda spark, sf: workloads.bucket_ablation(events_parts(spark, sf), [0.0, 0.5, 0.95]))
add("w7_redundancy_peak", lambda spark, sf: redundancy_peak(workloads.redundancy_by_load(events_parts(spark, sf))))
add("w12_document_sizes", lambda spark, sf: workloads.sweep(tables.parts_of(spark, sf, "documents"), ["state_driven", "rateless", "filter_rateless"], [0.0, 0.5, 1.0], [0.01]))


SWEPT = ["s", "protocol", "eps", "load_factor", "required_bytes", "redundant_bytes"]


def told_bytes(metrics: DataFrame, *plain: str) -> DataFrame:
    """The columns of a sweep that SQL gives too: the length of a stream of cells takes a decoder, so their metadata stay out."""
    return metrics.select(*SWEPT, F.when(F.col("protocol").isin(*plain), F.col("metadata_bytes")).alias("metadata_bytes"))


def told_sql(s: float, protocol: str, eps: float | None, load: float | None, redundant: str = "0", metadata: str = "null") -> str:
    number = lambda x: "null::double" if x is None else f"{x}::double"
    need = "(select coalesce(sum(nbytes), 0)::bigint from p where side <> 'both')"
    return f"select {s}::double as s, '{protocol}' as protocol, {number(eps)} as eps, {number(load)} as load_factor, {need} as required_bytes, ({redundant})::bigint as redundant_bytes, ({metadata})::bigint as metadata_bytes"


def again(sent: str, has: str) -> str:
    return f"(select coalesce(sum(nbytes), 0) from {sent} where h in (select h from {has}))"


def plain_sweep_sql(similarities: list[float], loads: list[float]) -> str:
    rows = []
    for s in similarities:
        rows += [f"{plain_buckets(1.0, s)} {told_sql(s, 'state_driven', None, None, again('a', 'b'), '0')} union all {told_sql(s, 'rateless', None, None)}"]
        for f in loads:
            cost = f"(select n * {WIRE.digest} from nb) + (select count(*) * {WIRE.bucket_index} from bad)"
            rows.append(f"{plain_buckets(f, s)} {told_sql(s, 'bucketed', None, f, again('whole_b', 'a'), cost)} union all {told_sql(s, 'bucketed_rateless', None, f, again('whole_b', 'a'))}")
    return " union all ".join(f"select * from ({row})" for row in rows)


def filtered_sweep_sql(similarities: list[float], shares: list[float], loads: list[float]) -> str:
    rows = []
    for s in similarities:
        for e in shares:
            filters = f"{BYTES_A} + {BYTES_B}"
            rows.append(f"{split_ctes(s=s, eps=e)} {told_sql(s, 'filter_rateless', e, None)}")
            for f in loads:
                ctes = f"{split_ctes(s=s, eps=e)}, {bucket_ctes('com_a', 'com_b', 'com_b', f)}"
                cost = f"{filters} + (select n * {WIRE.digest} from nb) + (select count(*) * {WIRE.bucket_index} from bad)"
                twice = again("whole_a", "b")
                rows.append(f"{ctes} {told_sql(s, 'filter_bucketed', e, f, twice, cost)} union all {told_sql(s, 'filter_bucketed_rateless', e, f, twice)}")
    return " union all ".join(f"select * from ({row})" for row in rows)


SOME, SHARES, LOADS = [0.0, 0.45, 0.75, 0.93, 1.0], [0.01, 0.25], [0.2, 1.0, 5.0]
add("w1_bytes", lambda spark, sf: told_bytes(workloads.without_filters(events_parts(spark, sf)), "state_driven", "bucketed"), plain_sweep_sql(workloads.SIMILARITIES, LOADS))
add("w2_bytes", lambda spark, sf: told_bytes(workloads.with_filters(events_parts(spark, sf), similarities=SOME, eps=SHARES, load_factors=[0.2, 5.0]), "filter_bucketed"), filtered_sweep_sql(SOME, SHARES, [0.2, 5.0]))


@query("w13_natural_events", f"select (select count(*) from ({NATURAL_A} except {NATURAL_B})) + (select count(*) from ({NATURAL_B} except {NATURAL_A})) as n_items, (select sum(octet_length(encode(payload))) from (({NATURAL_A} except {NATURAL_B}) union all ({NATURAL_B} except {NATURAL_A})))::bigint as payload_bytes")
def w13_natural_events(spark, sf):
    r = Replicas.single(*replicas.sides(snapshot(replicas.natural_events(spark, sf), "pair")))
    return PROTOCOLS["filter_rateless"](r).transcript.agg(F.sum("n_items").alias("n_items"), F.sum("payload_bytes").alias("payload_bytes"))


@query("w17_uniform_strings", f"select 0::bigint as apart, count(*) as parts from (select distinct substr(concat(h, sha256(payload), sha256(payload || '+')), 1, cast(20 + d % 45 as int)) from ({digests_sql(items_sql('lineitem'))}))")
def w17_uniform_strings(spark, sf):
    strings = replicas.uniform_strings(tables.load_items(spark, sf, "lineitem"), 20, 64).distinct()
    parts = with_digest(strings.withColumn("nbytes", F.octet_length("payload")))
    result = PROTOCOLS["filter_rateless"](Replicas.single(*replicas.sides(snapshot(replicas.make_pair(parts, 0.9), "pair")), SyncConfig(segments=8)), SyncConfig(segments=8))
    n = parts.count()
    return converged(result).select("apart", F.lit(n).cast("bigint").alias("parts"))


add("reduction_vs_state_driven", lambda spark, sf: reduction(workloads.sweep(events_parts(spark, sf), ["state_driven", "filter_rateless"], [0.5, 0.95, 1.0], [0.01]), "state_driven").select("s", "protocol", "total_bytes", "ratio", "saving"))


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """METRIC row of filters with coded cells at 1 % on events, similarity three quarters."""
    r = replicas_of(spark, sf)
    result = PROTOCOLS["filter_rateless"](r)
    return summarise(result.transcript).join(converged(result), "sid").crossJoin(replicas.jaccard(r.a, r.b).select("similarity")).drop("sid")


add("flagship", flagship)


@query("engine_costs")
def engine_costs(spark, sf):
    """Stages, rows, shuffled and spilled bytes and seconds of four protocols on the same pair."""
    out = None
    for protocol in ("state_driven", "bucketed", "rateless", "filter_rateless"):
        r = replicas_of(spark, sf)
        cost = engine_cost(spark, lambda: PROTOCOLS[protocol](r).transcript.write.format("noop").mode("overwrite").save())  # noqa: B023
        row = cost.agg(F.lit(protocol).alias("protocol"), F.count("*").alias("stages"), *[F.sum(c).alias(c) for c in ("rows_read", "shuffle_rows", "shuffle_bytes", "spilled_bytes", "task_seconds")], F.max("wall_seconds").alias("wall_seconds"))
        out = row if out is None else out.unionByName(row)
    return out
