"""The behaviour that the experiments report, on events at the smallest scale and by the closed form."""

import pytest

from replica_sync.plans import costmodel, workloads
from replica_sync.sources import tables

S = [0.0, 0.25, 0.5, 0.75, 0.95, 1.0]


@pytest.fixture(scope="module")
def measured(spark, sf):
    parts = tables.snapshot(tables.parts_of(spark, sf, "events"))
    rows = workloads.sweep(parts, ["state_driven", "bucketed", "rateless", "filter_rateless", "bucketed_rateless"], S, [0.01, 0.25], [0.2, 5.0]).collect()
    return {(r["protocol"], r["s"], r["eps"], r["load_factor"]): r for r in rows}


def total(m, protocol, s, eps=None, f=None):
    return m[protocol, s, eps, f]["total_bytes"]


def test_cells_send_nothing_twice(measured):
    assert all(measured["rateless", s, None, None]["redundant_bytes"] == 0 for s in S)


def test_buckets_with_and_without_cells_are_equally_redundant(measured):
    for s in S:
        for f in (0.2, 5.0):
            assert measured["bucketed", s, None, f]["redundant_bytes"] == measured["bucketed_rateless", s, None, f]["redundant_bytes"]


def test_bucket_metadata(measured):
    meta = lambda p, s: measured[p, s, None, 0.2]["metadata_bytes"]
    assert meta("bucketed_rateless", 0.0) > meta("bucketed", 0.0) and meta("bucketed_rateless", 1.0) < meta("bucketed", 1.0)


def test_finer_buckets_are_less_redundant(measured):
    assert max(measured["bucketed", s, None, 5.0]["redundant_bytes"] for s in S) < max(measured["bucketed", s, None, 0.2]["redundant_bytes"] for s in S)


def test_whole_state_is_best_when_disjoint(measured):
    others = [r["total_bytes"] for k, r in measured.items() if k[1] == 0.0 and k[0] != "state_driven"]
    assert total(measured, "state_driven", 0.0) < min(others)


def test_cells_alone_are_best_when_equal(measured):
    cheapest = min((r["total_bytes"], k[0]) for k, r in measured.items() if k[1] == 1.0)
    assert cheapest[1] in ("rateless", "bucketed_rateless")


def test_cells_lose_below_half_and_win_above(measured):
    assert total(measured, "rateless", 0.25) > total(measured, "state_driven", 0.25)
    assert total(measured, "rateless", 0.75) < total(measured, "state_driven", 0.75)


def test_filter_saves_at_low_similarity(measured):
    saving = 1 - total(measured, "filter_rateless", 0.0, 0.01) / total(measured, "rateless", 0.0)
    assert 0.35 < saving < 0.52
    assert total(measured, "filter_rateless", 0.0, 0.25) < total(measured, "rateless", 0.0)
    assert 0.25 < 1 - total(measured, "filter_rateless", 0.75, 0.01) / total(measured, "rateless", 0.75) < 0.45


def test_larger_filters_errors_pay_at_high_similarity(measured):
    assert total(measured, "filter_rateless", 0.0, 0.01) < total(measured, "filter_rateless", 0.0, 0.25)
    assert total(measured, "filter_rateless", 0.95, 0.25) < total(measured, "filter_rateless", 0.95, 0.01)


def test_reduction_against_whole_state(measured):
    assert total(measured, "state_driven", 1.0) / total(measured, "filter_rateless", 1.0, 0.01) > 15


def test_closed_form(spark):
    rows = {r["s"]: r for r in costmodel.predicted(costmodel.grid(spark, [0.0, 0.75, 0.93, 0.94, 1.0], [0.01], [0.2])).collect()}
    saving = lambda s: 1 - rows[s]["filter_rateless"] / rows[s]["rateless"]
    assert abs(saving(0.0) - 0.449) < 0.005 and abs(saving(0.75) - 0.358) < 0.005
    assert rows[0.93]["filter_rateless"] < rows[0.93]["rateless"] and rows[0.94]["filter_rateless"] > rows[0.94]["rateless"]
    assert abs(rows[1.0]["state_driven"] / rows[1.0]["filter_rateless"] - 17.7) < 0.1


def test_best_filter_grows_with_similarity():
    eps = [costmodel.optimal_eps(s) for s in (0.0, 0.5, 0.75, 0.9)]
    assert eps == sorted(eps) and costmodel.optimal_eps(1.0) == 1.0 and abs(eps[0] - 0.004) < 0.001


def test_advice():
    assert costmodel.advise(0.0).protocol == "state_driven"
    assert costmodel.advise(0.5).protocol == "filter_rateless"
    assert costmodel.advise(0.995).protocol == "rateless"


def test_measured_follows_the_closed_form(spark, measured):
    mbar = total(measured, "state_driven", 1.0) / 500
    rows = {r["s"]: r for r in costmodel.predicted(costmodel.grid(spark, S, [0.01], [0.2], c=500, mbar=mbar)).collect()}
    for s in S[:-1]:
        assert abs(total(measured, "filter_rateless", s, 0.01) / rows[s]["filter_rateless"] - 1) < 0.08
        assert abs(total(measured, "bucketed", s, f=0.2) / rows[s]["bucketed"] - 1) < 0.08
