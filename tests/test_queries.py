"""Every registered query of the engine against DuckDB at the smallest scale."""

import math
from decimal import Decimal

import pytest

from replica_sync.plans import catalogue

QUERIES, ORACLES = catalogue.queries(), catalogue.oracle_sql()
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: Sweeps and repeated ways of choosing partners: run by hand and by the driver, smaller cases are in other tests.
SLOW = {"gossip_random", "gossip_similarity", "gossip_topology", "gossip_ring", "w1_no_filter", "w2_filter", "w2_bytes", "w3_high_similarity", "w4_best_four", "w5_filter_ablation", "w6_bucket_ablation", "w7_redundancy_peak", "w12_document_sizes"}


@pytest.fixture(scope="module")
def duck(sf):
    import duckdb

    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return con


def plain(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else float(f"{v:.9g}")
    return int(v) if isinstance(v, Decimal) and v == v.to_integral() else v


@pytest.mark.parametrize("name", [n for n in QUERIES if n in ORACLES and n not in SLOW])
def test_against_sql(spark, sf, duck, name):
    df = QUERIES[name](spark, sf)
    names = sorted(df.columns)
    got = sorted((tuple(plain(r[c]) for c in names) for r in df.collect()), key=repr)
    found = duck.sql(ORACLES[name])
    assert sorted(found.columns) == names
    want = sorted((tuple(plain(r[found.columns.index(c)]) for c in names) for r in found.fetchall()), key=repr)
    assert got == want


@pytest.mark.parametrize("name", [n for n in QUERIES if n not in ORACLES and n not in SLOW])
def test_runs(spark, sf, name):
    assert QUERIES[name](spark, sf).count() >= 1


@pytest.mark.parametrize("name", ["best_protocol_by_similarity", "crossover_points", "op_cross_grid", "op_math_fns", "op_recursive", "optimal_eps", "predict_grid"])
def test_reads_a_given_table(spark, sf, name):
    plan = QUERIES[name](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "parquet" in plan
