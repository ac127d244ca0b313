"""Exact counters: joins in pattern order, the same with a counted last step, and time buckets with a halo."""

from __future__ import annotations

from collections import defaultdict
from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tmotif.functions.motif import Motif, motif
from tmotif.operators.cycles import is_cycle
from tmotif.operators.dense import dense_counts, fitting, is_dense
from tmotif.operators.extend import _all
from tmotif.sources.graph import TemporalGraph


def _bucket(c: str, width: int) -> str:
    return f"{c} div {width} - if({c} % {width} < 0, 1, 0)"


def _room(m: Motif, done: list[int], p: int, delta: int, step: int):
    """The first and the last time that pattern edge p may have beside the positions done."""
    before, after = [F.col(f"t{q}") for q in done if q < p], [F.col(f"t{q}") for q in done if q > p]
    every = [F.col(f"t{q}") for q in done]
    early, late = (F.least(*every), F.greatest(*every)) if len(every) > 1 else (every[0], every[0])
    return reduce(F.greatest, [c + step for c in before], late - delta), reduce(F.least, [c - step for c in after], early + delta)


def _extended(state: DataFrame, edges: DataFrame, m: Motif, done: list[int], p: int, delta: int, keys: list[str], ties: str) -> DataFrame:
    """Joins pattern edge p to partial matches of the positions done; an equi-join on what is bound and the time bucket."""
    a, b = m.edges[p]
    bound = {x for q in done for x in m.edges[q]}
    width, step = max(1, delta), 1 if ties == "strict" else 0
    lo, hi = _room(m, done, p, delta, step)
    state = state.withColumn("lo", lo).withColumn("hi", hi).where("lo <= hi").withColumn("bucket", F.explode(F.sequence(F.expr(_bucket("lo", width)), F.expr(_bucket("hi", width)))))
    own = edges.select(*keys, F.col("eid").alias(f"e{p}"), F.col("src").alias("s_"), F.col("dst").alias("d_"), F.col("t").alias(f"t{p}"), F.expr(_bucket("t", width)).alias("bucket"))
    on = [*keys, "bucket"]
    tests = [F.col(f"t{p}").between(F.col("lo"), F.col("hi"))]
    if ties != "strict":
        tests += [F.col(f"e{p}") != F.col(f"e{q}") for q in done]
    for end, x in (("s_", a), ("d_", b)):
        if x in bound:
            own = own.withColumnRenamed(end, f"v_{x}")
            on.append(f"v_{x}")
        else:
            own = own.withColumnRenamed(end, f"v_{x}")
            tests += [F.col(f"v_{x}") != F.col(f"v_{y}") for y in sorted(bound)]
    # partial matches are many more than the tables they come from, whose sizes the planner takes for theirs
    return state.hint("merge").join(own, on).where(_all(tests)).drop("lo", "hi", "bucket")


def _roots(edges: DataFrame, m: Motif, p: int, keys: list[str]) -> DataFrame:
    a, b = m.edges[p]
    return edges.select(*keys, F.col("eid").alias(f"e{p}"), F.col("t").alias(f"t{p}"), F.col("src").alias(f"v_{a}"), F.col("dst").alias(f"v_{b}")).where(F.col(f"v_{a}") != F.col(f"v_{b}"))


def connected_order(m: Motif, n: int, start: int = 0) -> list[int]:
    """The first n positions from start on: the earliest that closes two bound vertices, else the earliest that has one, so that no join is on time alone."""
    order, left = [start], [p for p in range(n) if p != start]
    while left:
        bound = {x for q in order for x in m.edges[q]}
        order.append(max(left, key=lambda p: (len(bound & {*m.edges[p]}), -p)))
        left.remove(order[-1])
    return order


def matches(tg: TemporalGraph, which: str | Motif, delta: int, keys: list[str] | None = None, start: int = 0, roots: DataFrame | None = None, ties: str = "strict") -> DataFrame:
    """All matches: keys, e0.., t0.., v_A...

    The joins start at a position and follow pattern order as far as each edge meets one before it; keys keep groups of edges (windows) apart.
    """
    m, keys = motif(which), keys or []
    order = connected_order(m, len(m.edges), start)
    state = _roots(tg.edges if roots is None else roots, m, start, keys)
    for i, p in enumerate(order[1:], 1):
        state = _extended(state, tg.edges, m, order[:i], p, delta, keys, ties)
    return state


def matches_by_halves(tg: TemporalGraph, which: str | Motif, delta: int) -> DataFrame:
    """The columns of matches() for a pattern whose first four edges are a cycle A > B > C > D > A: two wedges that share their ends A and C, so that no path of three edges is a row."""
    m = motif(which)
    if not is_cycle(Motif(m.edges[:4])) or len(m.vertices) != 4:
        raise ValueError("the pattern does not begin with a cycle of four edges")
    a, b, c, d = (x for x, _ in m.edges[:4])
    width = 4 * max(1, delta)
    first = _extended(_roots(tg.edges, m, 0, []), tg.edges, m, [0], 1, delta, [], "strict")
    second = _extended(_roots(tg.edges, m, 2, []), tg.edges, m, [2], 3, delta, [], "strict").withColumn("bucket", F.expr(_bucket("t2", width)))
    first = first.withColumn("from", F.expr("t1 + 1")).withColumn("till", F.expr(f"t0 + {delta} - 1")).where("from <= till")
    first = first.withColumn("bucket", F.explode(F.sequence(F.expr(_bucket("from", width)), F.expr(_bucket("till", width))))).drop("from", "till")
    state = first.hint("merge").join(second, [f"v_{a}", f"v_{c}", "bucket"]).where((F.col(f"v_{b}") != F.col(f"v_{d}")) & F.expr(f"t2 > t1 and t3 <= t0 + {delta}")).drop("bucket")
    for p in range(4, len(m.edges)):
        state = _extended(state, tg.edges, m, [*range(p)], p, delta, [], "strict")
    return state


def listed(tg: TemporalGraph, which: str | Motif, delta: int) -> DataFrame:
    """matches(), by halves where the third join would still close nothing."""
    m = motif(which)
    order = connected_order(m, len(m.edges))
    closes = len(order) > 2 and {*m.edges[order[2]]} <= {x for q in order[:2] for x in m.edges[q]}
    four = len(m.vertices) == 4 and len(m.edges) >= 4 and is_cycle(Motif(m.edges[:4]))
    return matches_by_halves(tg, m, delta) if four and not closes else matches(tg, m, delta)


def match_rows(found: DataFrame, which: str | Motif) -> DataFrame:
    """eids, vertices, t_first, t_last of matches."""
    m = motif(which)
    spots = range(len(m.edges))
    names = F.create_map(*[x for v in m.vertices for x in (F.lit(v), F.col(f"v_{v}"))])
    return found.select(F.array(*[f"e{p}" for p in spots]).alias("eids"), names.alias("vertices"), F.col("t0").alias("t_first"), F.col(f"t{len(m.edges) - 1}").alias("t_last"))


def _count(df: DataFrame, m: Motif, delta: int) -> DataFrame:
    return df.select(F.lit(m.name).alias("motif"), F.lit(delta).cast("bigint").alias("delta"), F.coalesce("count", F.lit(0)).cast("bigint").alias("count"))


def _dense(tg: TemporalGraph, m: Motif, delta: int) -> DataFrame:
    """The count is decimal(38,0) where it passes 63 bits."""
    found = fitting(dense_counts(tg, m, delta).select(F.col("found").alias("count")), "count")
    return found.select(F.lit(m.name).alias("motif"), F.lit(delta).cast("bigint").alias("delta"), "count")


def exact_backtrack(tg: TemporalGraph, which: str | Motif, delta: int, ties: str = "strict") -> DataFrame:
    """One row: motif, delta, count; every match is a row of the last join, unless they are too many for rows (see is_dense)."""
    m = motif(which)
    if ties == "strict" and is_dense(tg, m, delta):
        return _dense(tg, m, delta)
    return _count(matches(tg, m, delta, ties=ties).agg(F.count(F.lit(1)).alias("count")), m, delta)


def exact_frontier(tg: TemporalGraph, which: str | Motif, delta: int) -> DataFrame:
    """The same count: partial matches that ask the same of the edge that comes last (see connected_order) are one row with a multiplicity before the last join."""
    m = motif(which)
    if is_dense(tg, m, delta):
        return _dense(tg, m, delta)
    *order, last = connected_order(m, len(m.edges))
    state = _roots(tg.edges, m, 0, [])
    for i, p in enumerate(order[1:], 1):
        state = _extended(state, tg.edges, m, order[:i], p, delta, [], "strict")
    a, b = m.edges[last]
    bound = {x for q in order for x in m.edges[q]}
    asked = [f"v_{x}" for x in sorted(bound)] if not {a, b} <= bound else [f"v_{a}", f"v_{b}"]
    width = max(1, delta)
    lo, hi = _room(m, order, last, delta, 1)
    folded = state.withColumn("lo", lo).withColumn("hi", hi).where("lo <= hi").groupBy(*asked, "lo", "hi").agg(F.count(F.lit(1)).alias("times"))
    folded = folded.withColumn("bucket", F.explode(F.sequence(F.expr(_bucket("lo", width)), F.expr(_bucket("hi", width)))))
    own = tg.edges.select(F.col("src").alias(f"v_{a}"), F.col("dst").alias(f"v_{b}"), "t", F.expr(_bucket("t", width)).alias("bucket"))
    on = ["bucket", *[f"v_{x}" for x in (a, b) if x in bound]]
    tests = [F.col("t").between(F.col("lo"), F.col("hi"))]
    for x in (a, b):
        if x not in bound:
            tests += [F.col(f"v_{x}") != F.col(f"v_{y}") for y in sorted(bound)]
    return _count(folded.hint("merge").join(own, on).where(_all(tests)).agg(F.sum("times").alias("count")), m, delta)


def _search(m: Motif, delta: int, lo: int, hi: int):
    """Counts matches whose first edge has lo <= t < hi among one bucket's edges."""

    def count(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("t", kind="stable")
        by: dict = defaultdict(list)
        for s, d, t in zip(pdf["src"], pdf["dst"], pdf["t"], strict=True):
            by[s, d].append((t, s, d))
            by[s, None].append((t, s, d))
            by[None, d].append((t, s, d))
            by[None, None].append((t, s, d))
        from bisect import bisect_right

        times = {k: [e[0] for e in v] for k, v in by.items()}
        base = int(pdf["base"].iloc[0])
        n = 0
        stack = [(0, {}, None, None)]
        while stack:
            p, bind, first, last = stack.pop()
            if p == len(m.edges):
                n += 1
                continue
            a, b = m.edges[p]
            key = bind.get(a), bind.get(b)
            rows = by.get(key, [])
            at = 0 if last is None else bisect_right(times[key], last) if rows else 0
            for t, s, d in rows[at:]:
                if first is not None and t > first + delta:
                    break
                if first is None and not base <= t < base + hi - lo:
                    continue
                new = dict(bind)
                new[a], new[b] = s, d
                if len(set(new.values())) == len(new):
                    stack.append((p + 1, new, t if first is None else first, t))
        return pd.DataFrame({"count": [n]})

    return count


def exact_bucketed(tg: TemporalGraph, which: str | Motif, delta: int, c: int = 4) -> DataFrame:
    """The same count by depth-first search inside time buckets of width c * delta; each carries the edges of the next delta as a halo, and owns the matches that begin in it."""
    m = motif(which)
    if is_dense(tg, m, delta):
        return _dense(tg, m, delta)
    width = max(1, c * delta)
    base = F.expr(f"({_bucket('t', width)}) * {width}")
    halo = F.when(F.col("t") - base <= delta, F.array(base, base - width)).otherwise(F.array(base))
    rows = tg.edges.select("src", "dst", "t", F.explode(halo).alias("base"))
    found = rows.groupBy("base").applyInPandas(_search(m, delta, 0, width), "count bigint")
    return _count(found.agg(F.sum("count").alias("count")), m, delta)
