"""Schemes, policies, measures and marks beside the plain estimate."""

import time

import pytest

from tmotif.functions.motif import CATALOG, EIGHT
from tmotif.operators import exact, incidence
from tmotif.operators.measures import guarded, relative_error
from tmotif.plans import estimate as plans
from tmotif.plans.estimate import estimate, estimate_seeds, heuristic_samples, pilot_samples, prepare, required_samples
from tmotif.sources.graph import TemporalGraph, reply_graph

SF = "/root/testdata/sf0.001"
DAY = 86_400_000_000


@pytest.fixture(scope="module")
def folded(spark):
    return reply_graph(spark, SF, 6).staged()


@pytest.mark.parametrize("count", [exact.exact_frontier, plans.census])
def test_two_days(folded, count):
    """The longer window of the smallest folded graph: counts of every motif."""
    want = {"TRI": 4983, "M3-0": 646, "M4-0": 8414, "M4-1": 9, "M4-2": 89, "M4-3": 139, "M4-4": 13, "M4-5": 3751}
    names = want if count is exact.exact_frontier else ("TRI", "M3-0", "M4-1", "M4-4")
    assert {n: count(folded, n, 2 * DAY).first()["count"] for n in names} == {n: want[n] for n in names}


def test_stderr_of_schemes(folded):
    """Over many seeds the spread of the estimates agrees with the standard errors."""
    p = prepare(folded, DAY, CATALOG["M4-0"].anchor().cls)
    for scheme, low, high in (("iid", 0.5, 1.8), ("without_replacement", 0.5, 1.8), ("stratified", 0.4, 1.8), ("poisson", 0.3, 1.5)):
        rows = [estimate(folded, "M4-0", DAY, 3_000, seed=s, scheme=scheme, prepared=p).first() for s in range(8)]
        mean = sum(r["estimate"] for r in rows) / len(rows)
        spread = (sum((r["estimate"] - mean) ** 2 for r in rows) / (len(rows) - 1)) ** 0.5
        stderr = sum(r["stderr"] for r in rows) / len(rows)
        assert abs(mean - 1052) < 4 * stderr / len(rows) ** 0.5 + 20
        assert low < spread / stderr < high, (scheme, spread, stderr)


def test_all_without_replacement(folded):
    """When draws cover nearly all paths the error shrinks to nothing."""
    row = estimate(folded, "M4-0", DAY, 150_000, scheme="without_replacement").first()
    assert row["k"] <= row["w_total"] == 15886 and abs(row["estimate"] - 1052) < 1 and row["stderr"] < 1.5


def test_seeds_equal_single_runs(folded):
    rows = {r["seed"]: r for r in estimate_seeds(folded, "M4-0", DAY, 700, (42, 7)).collect()}
    for seed in (42, 7):
        assert rows[seed]["cnt"] == estimate(folded, "M4-0", DAY, 700, seed=seed).first()["cnt"]
    none = estimate_seeds(folded.where("false"), "M4-0", DAY, 10, (1, 2)).collect()
    assert sorted((r["seed"], r["estimate"]) for r in none) == [(1, 0.0), (2, 0.0)]


def test_anchor_policies(spark):
    """Few paths with many completions each against more paths with one each: the two policies part."""
    m = CATALOG["LATE"]  # A>B, C>D, B>C, D>A
    rows = [(0, 1, 0), (2, 3, 1), (1, 2, 2)] + [(3, 0, 3 + k) for k in range(30)]
    # edges that make wedges of the other anchors frequent, but complete nothing
    rows += [(9, 3, 40 + k) for k in range(12)] + [(0, 8, 60 + k) for k in range(3)]
    tg = TemporalGraph.from_rows(spark, rows)
    few, small = plans.choose_anchor(tg, m, 200, "min_W"), plans.choose_anchor(tg, m, 200, "min_WB", k=4_000)
    cost = {a: (prepare(tg, 200, a.cls).w_total, plans.pilot(tg, m, 200, 4_000, anchor=a.positions)["b"]) for a in m.anchors()}
    assert cost[few][0] == min(w for w, _ in cost.values())
    assert cost[small][0] * max(cost[small][1], 1) == min(w * max(b, 1) for w, b in cost.values())
    assert few != small


def test_heuristic(folded):
    k = pilot_samples(folded, "M4-0", DAY)
    assert 10 < k < 200 and pilot_samples(folded, "M4-1", DAY) is None
    assert heuristic_samples(3.0, 100.0, 7.0) == 43


def test_nothing_to_find():
    with pytest.raises(ValueError):
        required_samples(2, 1, 100, 0, 0.1, 0.05)
    with pytest.raises(ValueError):
        heuristic_samples(1, 1, 0)
    assert relative_error(3, 0) is None and relative_error(9, 10) == pytest.approx(0.1)


def test_marks(spark):
    assert guarded(spark, lambda: spark.range(10).count(), 60)[::2] == ("ok", 10)
    began = time.time()
    status, seconds, value = guarded(spark, lambda: spark.range(10**13).selectExpr("sum(sqrt(id))").first(), 1.5)
    assert status == "timeout" and value is None and time.time() - began < 30
    with pytest.raises(Exception, match="no_such"):
        guarded(spark, lambda: spark.sql("select no_such"), 60)
    assert spark.range(3).count() == 3


def test_multiplicity(folded):
    rows = folded.edges.collect()
    want = [sum(f["src"] == e["src"] and f["dst"] == e["dst"] and e["t"] <= f["t"] <= e["t"] + DAY for f in rows) for e in rows]
    got = incidence.multiplicity(folded, DAY).first()
    assert got["sigma"] == max(want) == 7 and got["sigma_avg"] == pytest.approx(sum(want) / len(want))


def test_convergence(folded):
    rows = plans.convergence(folded, "M4-0", DAY, (500, 8_000), range(4)).collect()
    assert len(rows) == 8 and len(EIGHT) == 8
    error = lambda k: sum(abs(r["estimate"] - 1052) for r in rows if r["k"] == k)
    assert error(8_000) < error(500)
