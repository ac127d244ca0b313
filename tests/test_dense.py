"""Counts by running sums against the listing counters, on graphs small enough for both."""

import random

import numpy as np
import pytest

from tmotif.functions.motif import CATALOG, Motif
from tmotif.operators import dense, exact, measures, weights
from tmotif.plans.estimate import census
from tmotif.sources.graph import TemporalGraph, reply_graph

SF = "/root/testdata/sf0.001"
DAY = 86_400_000_000


@pytest.fixture(scope="module")
def folded(spark):
    tg = reply_graph(spark, SF, 6)
    return tg.with_edges(tg.edges.persist())


@pytest.mark.parametrize(("name", "days"), [("TRI", 1), ("M3-0", 2), ("M4-0", 1), ("M4-4", 2), ("M4-5", 1), ("LATE", 1), ("PATH", 1)])
def test_census_by_running_sums(folded, monkeypatch, name, days):
    want = census(folded, name, days * DAY).first()
    assert not dense.is_dense(folded, CATALOG[name], days * DAY)
    monkeypatch.setattr(dense, "MANY", 1)
    assert dense.is_dense(folded, CATALOG[name], days * DAY)
    assert census(folded, name, days * DAY).first() == want
    for f in (exact.exact_backtrack, exact.exact_frontier, exact.exact_bucketed):
        assert f(folded, name, days * DAY).first()["count"] == want["count"] == dense.dense_counts(folded, CATALOG[name], days * DAY).first()["found"]


@pytest.mark.parametrize("name", ["M4-0", "M4-5"])
def test_anchor_stats_by_running_sums(folded, monkeypatch, name):
    want = measures.anchor_stats(folded, name, DAY).first()
    monkeypatch.setattr(dense, "MANY", 1)
    got = measures.anchor_stats(folded, name, DAY).first()
    assert [round(float(x), 6) for x in got[1:]] == [round(float(x), 6) for x in want[1:]] and got["motif"] == name


def test_ties_negative_times_and_big_counts(spark, monkeypatch):
    """Equal times, times below zero, windows of one, and counts beyond 64 bits in between."""
    rnd = random.Random(8)
    rows = [(rnd.randrange(5), rnd.randrange(5), rnd.randrange(-12, 12)) for _ in range(160)]
    tg = TemporalGraph.from_rows(spark, [r for r in rows if r[0] != r[1]])
    for name in ("TRI", "M4-0", "M3-1"):
        for delta in (1, 5):
            want = exact.exact_backtrack(tg, name, delta).first()["count"]
            assert dense.dense_counts(tg, CATALOG[name], delta).first()["found"] == want
    one = TemporalGraph.from_rows(spark, [(k % 3, (k + 1) % 3, k // 3 if k < 3 else k) for k in range(600)])
    want = exact.exact_backtrack(one, "TRI", 60).first()["count"]
    monkeypatch.setattr(dense, "_most", lambda sizes: 1 << 70)
    assert dense.dense_counts(one, CATALOG["TRI"], 60).first()["found"] == want > 0


def test_joins_are_connected(spark):
    """Whatever edge a search starts from, each further one meets a bound vertex; counts stay the same."""
    for name, m in CATALOG.items():
        for start in range(len(m.edges)):
            order = exact.connected_order(m, len(m.edges), start)
            assert sorted(order) == list(range(len(m.edges))) and order[0] == start
            assert all({*m.edges[p]} & {x for q in order[:i] for x in m.edges[q]} for i, p in enumerate(order) if i), name
    tg = reply_graph(spark, SF)
    assert exact.exact_backtrack(tg, "LATE", 2 * DAY).first()["count"] == 593 == exact.exact_frontier(tg, "LATE", 2 * DAY).first()["count"]


def test_listed_paths_are_never_broadcast(spark):
    """Rows made by explode are taken for as few as the table they come from."""
    tg = reply_graph(spark, SF).staged()
    text = exact.exact_backtrack(tg, "M4-0", DAY)._jdf.queryExecution().optimizedPlan().toString()
    assert text.count("strategy=merge") >= 3
    text = census(tg, "M4-0", DAY)._jdf.queryExecution().optimizedPlan().toString()
    assert text.count("strategy=merge") >= 3


def test_required_samples_from_the_table(spark):
    """The bound's figures come from the events given, as the SQL's do."""
    import duckdb

    from tmotif.plans import oracles, queries

    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{SF}/events.parquet'")
    want = con.execute(oracles.oracle_sql()["required_samples"]).fetchall()
    assert sorted(tuple(r) for r in queries.queries()["required_samples"](spark, SF).collect()) == sorted(want)


def test_running_sums_over_own_rows(spark):
    """Placings are summed over the times of their own edges; the same numbers, in far fewer rows."""
    rng = np.random.default_rng(5)
    for size, span in ((60, 500), (200, 60), (4, 30)):
        times, row = np.unique(rng.integers(0, 2 * span, size), return_inverse=True)
        table = np.zeros((len(times) + 1, 25), np.int64)
        np.add.at(table, (row, rng.integers(0, 25, size)), 1)
        n = int(np.searchsorted(times, span))
        ends = np.searchsorted(times, times[:n] + span, "right")
        for name in ("TRI", "M3-1", "M4-0", "M4-1"):
            spots = dense._placings(CATALOG[name], 5)
            want = dense.chains([table[:-1, s] for s in spots], n, ends).sum(axis=0)
            cells, begin, stops = dense.own_rows(table, spots, n, ends)
            assert (dense.chains(cells, begin, stops).sum(axis=0) == want).all()
            assert len(cells[0]) < len(times) or size < 10


def test_bound_on_paths(folded):
    """Exact counters choose their way by a bound from whole buckets, never below W."""
    for name in ("TRI", "M3-0", "M4-0", "LATE"):
        for delta in (DAY // 4, 2 * DAY):
            cls = CATALOG[name].anchor().cls
            w = weights.total(weights.weights(folded, delta, cls))
            assert w <= dense.paths_at_most(folded, delta, cls) <= 30 * w


def test_counts_beyond_63_bits(spark, monkeypatch):
    """Counts that no bigint holds come whole, as decimals; those that fit stay bigint. Also where a bucket's sums pass 64 bits."""
    turns = 900
    tg = TemporalGraph.from_rows(spark, [(a, b, 6 * k + p) for k in range(turns) for p, (a, b) in enumerate([(0, 1), (1, 2), (2, 0), (0, 2), (2, 1), (1, 0)])]).staged()
    assert dense.is_dense(tg, CATALOG["M3-0"], 10**6)
    # by hand: chains through one order of edges, over Python's integers
    edges = sorted(((r["t"], r["src"], r["dst"]) for r in tg.edges.collect()))

    def by_hand(m):
        found = 0
        for place in ({"A": a, "B": b, "C": 3 - a - b} for a in range(3) for b in range(3) if a != b):
            steps, ways = [(place[x], place[y]) for x, y in m.edges], [1] + [0] * len(m.edges)
            for _, s, d in edges:
                for p in range(len(steps) - 1, -1, -1):
                    if steps[p] == (s, d):
                        ways[p + 1] += ways[p]
            found += ways[-1]
        return found

    want = {n: by_hand(CATALOG[n]) for n in ("TRI", "M3-0", "M3-1")}
    assert want["M3-0"] < 1 << 63
    nine = Motif.parse("AB BC CA AC CB BA AB BC CA", "NINE")
    wide = by_hand(nine)
    assert wide > 1 << 64
    for f in (exact.exact_backtrack, exact.exact_frontier, exact.exact_bucketed, census):
        row = f(tg, nine, 10**6)
        assert row.first()["count"] == wide and dict(row.dtypes)["count"] == "decimal(38,0)"
        row = f(tg, "M3-0", 10**6)
        assert row.first()["count"] == want["M3-0"] and dict(row.dtypes)["count"] == "bigint"
    ratios = measures.count_ratios(tg, 10**6, [(nine, "TRI")]).first()
    assert (ratios["above_count"], ratios["below_count"]) == (wide, want["TRI"]) and ratios["ratio"] == pytest.approx(wide / want["TRI"])
    rows = measures.count_table({"x": (tg, 10**6)}, [nine, "TRI"]).where("motif is null").collect()
    assert {r["count"] for r in rows} == {wide + want["TRI"]}


def test_wide_sums_are_exact():
    """Wrapped sums and doubles give what Python's integers give; doubles that are too far off are seen."""
    rng = np.random.default_rng(6)
    cells = [rng.integers(0, 1 << 12, (40, 3)) for _ in range(7)]
    ends = rng.integers(20, 41, 20)
    want = int(dense.chains([c.astype(object) for c in cells], 20, ends).sum())
    assert want > 1 << 64 and dense.all_chains(cells, 20, ends, want) == want
    for low, near in ((5, 5.0), ((1 << 64) - 1, 2.0**64), (7, 2.0**80), (0, 2.0**70 - 2.0**40)):
        got = dense._whole(low, near, 2.0**50)
        assert got % (1 << 64) == low and abs(got - int(near)) <= 1 << 50 or abs(got - int(near)) <= 1 << 63
    assert dense._whole(1, 2.0**100, 2.0**62) is None
    wide = [c << 14 for c in rng.integers(1, 1 << 12, (6, 40, 3))]
    want = int(dense.chains([c.astype(object) for c in wide], 20, ends).sum())
    assert dense.all_chains(list(wide), 20, ends, want) == want


def test_no_path_is_listed(spark, monkeypatch):
    """Counts and completions come from matches; before, each path of the anchor was a row."""
    from tmotif.operators import sampling
    from tmotif.plans import estimate, queries

    tg = reply_graph(spark, SF).staged()
    names = ("TRI", "M3-0", "M3-1", "M4-0", "M4-1", "M4-5", "LATE", "PAW")
    want = {n: exact.exact_backtrack(tg, n, 4 * DAY).first()["count"] for n in names}
    halves = exact.matches_by_halves(tg, "M4-0", 4 * DAY).select("e0", "e1", "e2", "e3")
    assert sorted(halves.collect()) == sorted(exact.matches(tg, "M4-0", 4 * DAY).select("e0", "e1", "e2", "e3").collect()) and halves.count() == want["M4-0"] > 0
    stats = {}
    for n in ("M4-0", "M4-5"):  # as from listed paths
        counted, w, _ = estimate.census_rows(tg, n, 4 * DAY)
        xs = np.array([r["x"] for r in counted.where("x > 0").select("x").collect()])
        stats[n] = [int(xs.max(initial=0)), len(xs), int(xs.sum()), xs.sum() / w]
    monkeypatch.setattr(sampling, "every_path", lambda *_: pytest.fail("a path is listed"))
    assert {r["motif"]: r["count"] for r in queries._counts(tg, names, 4 * DAY).collect()} == want
    for n, own in stats.items():
        row = measures.anchor_stats(tg, n, 4 * DAY).first()
        assert [row["b_max"], row["hits"], row["count"], pytest.approx(row["b_avg_all"])] == own
    none = measures.anchor_stats(tg, "M4-0", 1).first()
    assert (none["b_max"], none["hits"], none["count"], none["b_avg"]) == (0, 0, 0, None)


def test_spread_of_many_completions():
    """Squares beyond 64 bits, in linear work, against all pairs of start and end."""
    rng = np.random.default_rng(9)
    for name, most in (("M4-0", 40), ("M4-5", 40), ("TRI", 3), ("M4-5", 1 << 14)):
        m = CATALOG[name]
        first, size = dense.leading(m), len(m.edges)
        cells = [rng.integers(0, most, (30, 2)) * rng.integers(0, 2, (30, 2)) for _ in range(size)]
        ends = np.sort(rng.integers(15, 31, (15, 2)), axis=0)
        squares, high = 0, 0
        for a in range(2):
            own = [c[:, a].astype(object) for c in cells]
            for s in range(15):
                for e in range(s + 1, ends[s, a]):
                    times = own[0][s] * own[first - 1][e] * (own[1][s + 1 : e].sum() if first == 3 else 1)
                    x = sum(own[first][i] * (own[first + 1][i + 1 : ends[s, a]].sum() if size - first == 2 else 1) for i in range(e + 1, ends[s, a]))
                    squares += times * x * x
                    high = max(high, x if times else 0)
        assert dense._spread(cells, first, 15, ends) == (squares, high)
        assert most < 1 << 14 or squares > 1 << 64
