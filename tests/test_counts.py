"""Counts on hand-made graphs and against another engine, and the golden numbers of the fixtures."""

import duckdb
import pytest

from tmotif.functions.motif import CATALOG, AnchorError, Motif, PathClass, WedgeClass
from tmotif.operators import exact, weights
from tmotif.operators.baselines import estimate_edges, estimate_partition, estimate_windows
from tmotif.operators.incidence import windowed_degrees
from tmotif.operators.sampling import list_paths
from tmotif.plans.estimate import census, estimate, estimate_seeds, prepare, required_samples
from tmotif.sources.graph import TemporalGraph, reply_graph

SF = "/root/testdata/sf0.001"
DAY = 86_400_000_000
X1 = [(0, 1, 10), (1, 2, 30), (2, 3, 40), (3, 0, 90)]


def counts(spark, rows, name, delta, ties="strict"):
    tg = TemporalGraph.from_rows(spark, rows)
    got = {census(tg, name, delta, ties=ties).first()["count"], exact.exact_backtrack(tg, name, delta, ties).first()["count"]}
    assert len(got) == 1
    return got.pop()


@pytest.mark.parametrize(
    ("rows", "name", "delta", "want"),
    [
        (X1, "M4-0", 100, 1),
        (X1, "M4-0", 80, 1),
        (X1, "M4-0", 79, 0),
        ([*X1[:2], (3, 2, 40), X1[3]], "M4-0", 100, 0),
        ([X1[0], (1, 2, 80), *X1[2:]], "M4-0", 100, 0),
        ([*X1[:3], (3, 0, 200)], "M4-0", 100, 0),
        ([X1[0], (1, 2, 30), (2, 3, 30), X1[3]], "M4-0", 100, 0),
        ([*X1, (3, 0, 95), (1, 2, 35)], "M4-0", 100, 4),
        ([(0, 1, 1), (2, 3, 2), (1, 2, 3), (3, 0, 4)], "LATE", 10, 1),
        ([(0, 1, 1), (2, 3, 2), (1, 2, 3), (3, 0, 4)], "M4-0", 10, 0),
    ],
)
def test_hand_made(spark, rows, name, delta, want):
    assert counts(spark, rows, name, delta) == want


def test_weak_ties(spark):
    assert counts(spark, [X1[0], (1, 2, 30), (2, 3, 30), X1[3]], "M4-0", 100, "weak") == 1


def test_nine_edges(spark):
    path = [(0, 1), (1, 2), (2, 3), (3, 2), (2, 1), (1, 0), (0, 1), (1, 2), (2, 3)]
    tg = TemporalGraph.from_rows(spark, [(a, b, t) for t, (a, b) in enumerate(path)])
    assert [census(tg, "M4-1", d).first()["count"] for d in (8, 7)] == [1, 0]


def test_star(spark):
    tg = TemporalGraph.from_rows(spark, [(0, 1, 1), (0, 2, 2), (0, 3, 3)])
    with pytest.raises(AnchorError):
        estimate(tg, "STAR", 5, 10)
    assert [exact.exact_backtrack(tg, "STAR", d).first()["count"] for d in (2, 1)] == [1, 0]
    assert estimate(tg, "STAR", 2, 200, sampler="hub").first()["estimate"] == pytest.approx(1, abs=0.5)


def test_empty_and_flat(spark):
    empty = TemporalGraph.from_rows(spark, X1).where("false")
    flat = TemporalGraph.from_rows(spark, [(0, 1, 5), (1, 2, 5), (2, 3, 5), (3, 0, 5)])
    for tg in (empty, flat):
        assert estimate(tg, "M4-0", 10, 50).first()["estimate"] == 0
        assert census(tg, "M4-0", 10).first()["count"] == 0
    with pytest.raises(ValueError):
        estimate(flat, "M4-0", 10, 0)


@pytest.fixture(scope="module")
def replies(spark):
    tg = reply_graph(spark, SF)
    return tg.with_edges(tg.edges.persist())


@pytest.fixture(scope="module")
def folded(spark):
    tg = reply_graph(spark, SF, 6)
    return tg.with_edges(tg.edges.persist())


def test_golden_totals(replies, folded):
    got = {r["class"]: r["w_total"] for r in weights.totals(replies, 2 * DAY).collect()}
    assert got["--<<"] == 12_723 and got["-+<>"] == 12_669 and got["++>>"] == 12_461 and got["+-><"] == 12_054
    got = {r["class"]: r["w_total"] for r in weights.totals(folded, DAY, WedgeClass.all()).collect()}
    assert got == {"src-<": 3464, "src->": 3518, "src+<": 3382, "src+>": 3382, "dst-<": 3302, "dst->": 3302, "dst+<": 3518, "dst+>": 3464}


@pytest.mark.parametrize("ties", ["strict", "closed"])
def test_degrees_agree(replies, ties):
    cls = PathClass("-", "+", "<", ">")
    sweep = windowed_degrees(replies, DAY, cls, ties=ties).select("eid", "n1", "n3")
    rows = {r["eid"]: (r["n1"], r["n3"]) for r in sweep.collect()}
    edges = replies.edges.collect()
    for e in edges[::40]:
        if ties == "strict":
            want = sum(f["dst"] == e["src"] and e["t"] - DAY <= f["t"] < e["t"] for f in edges), sum(f["src"] == e["dst"] and e["t"] < f["t"] <= e["t"] + DAY for f in edges)
        else:
            want = sum(f["dst"] == e["src"] and e["t"] - DAY <= f["t"] <= e["t"] for f in edges), sum(f["src"] == e["dst"] and e["t"] <= f["t"] <= e["t"] + DAY for f in edges)
        assert rows[e["eid"]] == want
    if ties == "strict":
        frame = {r["eid"]: (r["n1"], r["n3"]) for r in windowed_degrees(replies, DAY, cls, impl="frame").select("eid", "n1", "n3").collect()}
        assert frame == rows


def test_ids_are_a_bijection(replies):
    cls = PathClass("-", "+", "<", ">")
    prepared = prepare(replies, 2 * DAY, cls, buckets=7)
    paths = list_paths(replies, prepared.centers, 2 * DAY, cls)
    assert prepared.w_total == 12_669 == paths.select("eid1", "eid2", "eid3").distinct().count() == paths.select("path_id").distinct().count()


def test_golden_estimate(replies):
    row = estimate(replies, "M4-0", 2 * DAY, 20_000).first()
    assert round(row["estimate"], 4) == 476.3544 and round(row["valid_rate"] * 20_000) == 7543


@pytest.mark.parametrize(("name", "want"), [("TRI", 1264), ("M3-0", 21), ("M4-0", 1052), ("M4-5", 257), ("PAW", 1103), ("LATE", 1136), ("SPLIT", 1108)])
def test_exact_counters_agree(folded, name, want):
    got = [census(folded, name, DAY), exact.exact_backtrack(folded, name, DAY), exact.exact_frontier(folded, name, DAY), exact.exact_bucketed(folded, name, DAY)]
    assert [g.first()["count"] for g in got] == [want] * 4


def test_every_anchor_gives_the_same(folded):
    for name in ("M4-5", "LATE"):
        assert len({census(folded, name, DAY, anchor=a.positions).first()["count"] for a in CATALOG[name].anchors()}) == 1


def test_chain_impls(folded):
    assert {census(folded, "M3-1", DAY, impl=i).first()["count"] for i in ("fold", "window", "arrow")} == {19}


def test_samplers_are_close(folded, replies):
    row = estimate(folded, "M4-0", DAY, 20_000, sampler="constrained").first()
    assert abs(row["estimate"] - 1052) <= 5 * row["stderr"] and row["valid_rate"] > 0.3
    rates = [estimate(replies, "M4-0", 2 * DAY, 5_000, sampler=s).first()["valid_rate"] for s in ("static", "centered", "constrained")]
    assert rates == sorted(rates)
    for got in (estimate_windows(folded, "M4-0", DAY, 60, variant="A"), estimate_windows(folded, "M4-0", DAY, 60, variant="E"), estimate_partition(folded, "M4-0", DAY), estimate_edges(folded, "M4-0", DAY, 0.5)):
        assert 400 < got.first()["estimate"] < 2100


def test_unbiased_over_seeds(folded):
    rows = estimate_seeds(folded, "M4-0", DAY, 4_000, range(6)).collect()
    mean = sum(r["estimate"] for r in rows) / len(rows)
    assert abs(mean - 1052) < 4 * rows[0]["stderr"] / len(rows) ** 0.5 + 30


def test_partitioning_does_not_matter(spark, replies):
    again = replies.with_edges(replies.edges.repartition(13, "eid"))
    assert estimate(again, "TRI", DAY, 3_000).collect() == estimate(replies, "TRI", DAY, 3_000).collect()


def test_metamorphic(spark, folded):
    base = census(folded, "M4-5", DAY).first()["count"]
    moved = folded.with_edges(folded.edges.selectExpr("eid", "src * 7 + 3 as src", "dst * 7 + 3 as dst", "t - 1704112402016549 as t"))
    back = folded.with_edges(folded.edges.selectExpr("eid", "dst as src", "src as dst", "-t as t"))
    assert census(moved, "M4-5", DAY).first()["count"] == base == exact.exact_backtrack(back, CATALOG["M4-5"].reversed(), DAY).first()["count"]


def test_bound():
    assert required_samples(2, 1, 100, 10, 0.1, 0.05) == 22134


def test_random_motif_against_duckdb(spark, replies):
    from tmotif.plans.oracles import self_join

    m = Motif.parse("AB CB BD AC", "own")
    con = duckdb.connect()
    con.register("edges", replies.edges.select("eid", "src", "dst", "t").toPandas())
    tables, tests = self_join(m, 2 * DAY)
    want = con.execute(f"SELECT count(*) FROM {tables} WHERE {tests}").fetchone()[0]
    assert census(replies, m, 2 * DAY).first()["count"] == want == exact.exact_backtrack(replies, m, 2 * DAY).first()["count"]
