"""Cycles by wedges around vertices of low degree, against the joins in pattern order."""

import random

import pytest

from tmotif.functions.motif import CATALOG, Motif
from tmotif.operators import cycles
from tmotif.operators.exact import matches
from tmotif.plans.estimate import census_count
from tmotif.sources.graph import TemporalGraph, trade_graph

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize(("vertices", "edges", "hub"), [(9, 160, 0.3), (25, 260, 0.5)])
def test_cycles_equal_the_joins(spark, vertices, edges, hub):
    rng = random.Random(vertices)
    end = lambda: 0 if rng.random() < hub else rng.randrange(vertices)
    rows = [(end(), end(), rng.randrange(-40, 40)) for _ in range(edges)]
    tg = TemporalGraph.from_rows(spark, [*rows, *rows[:20]])
    tg = tg.with_edges(tg.without_loops().edges.persist())
    for name in ("TRI", "M4-0"):
        for delta in (6, 25):
            want = matches(tg, name, delta).count()
            assert census_count(tg, name, delta).first() == (name, delta, want)
    assert cycles.cycle_count(tg, "TRI", 0).first()["count"] == 0


def test_a_hub_forms_no_wedges(spark):
    """A thousand edges into a hub and out of it are a million paths; around its neighbours there is one wedge each."""
    rows = [(0, k, 2) for k in range(1, 1001)] + [(k, 0, 1) for k in range(1, 1001)]
    edges = cycles.ordered_edges(TemporalGraph.from_rows(spark, [*rows, *[(k, -k, 3) for k in range(1, 1001)]]))
    found = cycles.wedges(*cycles._roles(edges), 5, both=False)
    assert found.where("c = 0").isEmpty() and found.count() <= 1000
    assert cycles._threes(edges, 5).first()["count"] == 0


def test_trade_graph_without_numbers(spark):
    whole, thin = trade_graph(spark, SF), trade_graph(spark, SF, numbered=False)
    assert thin.edges.columns == ["src", "dst", "t"]
    assert whole.edges.select("src", "dst", "t").exceptAll(thin.edges).isEmpty() and whole.edges.count() == thin.edges.count()
    closing = cycles.ordered_edges(thin).where("if(up, src_under, dst_under)").count()
    assert closing < thin.edges.count() and census_count(thin, "TRI", 30).first()["count"] == 0


def test_other_patterns_are_no_cycles():
    assert [n for n, m in CATALOG.items() if cycles.is_cycle(m)] == ["M4-0", "TRI"]
    assert not cycles.is_cycle(Motif.parse("AB CA BC"))
    with pytest.raises(ValueError):
        cycles.cycle_count(None, "LATE", 1)
