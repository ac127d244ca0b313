"""Checking anchors, and counting without listing the ways to complete them."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from tmotif.functions.motif import Anchor, Motif
from tmotif.sources.graph import TemporalGraph


def _all(tests: list[Column]) -> Column:
    return reduce(lambda a, b: a & b, tests, F.lit(True))


def anchor_times(anchor: Anchor) -> dict[int, str]:
    """Pattern position -> time column of the anchor's rows."""
    return {p: f"t{k}" for k, p in enumerate(anchor.positions, 1)}


def vertex_columns(anchor: Anchor) -> dict[str, str]:
    return {v: f"v{k}" for k, v in enumerate(anchor.vertices)}


def is_valid(anchor: Anchor, delta: int, ties: str = "strict") -> Column:
    """Distinct vertices, pattern order of the anchor's times, and the window."""
    vs = [*vertex_columns(anchor).values()]
    tests = [F.col(a) != F.col(b) for i, a in enumerate(vs) for b in vs[:i]]
    times = [c for _, c in sorted(anchor_times(anchor).items())]
    tests += [F.col(a) < F.col(b) if ties == "strict" else F.col(a) <= F.col(b) for a, b in zip(times, times[1:], strict=False)]
    return _all([*tests, F.col(times[-1]) - F.col(times[0]) <= delta])


def check_paths(paths: DataFrame, anchor: Anchor, delta: int, ties: str = "strict") -> DataFrame:
    return paths.withColumn("valid", is_valid(anchor, delta, ties))


def demands(paths: DataFrame, motif: Motif, anchor: Anchor, delta: int, ties: str = "strict") -> DataFrame:
    """A row for each valid path and free position: draw, pos, src, dst, lo, hi; a fitting edge has lo <= t <= hi."""
    times, where = anchor_times(anchor), vertex_columns(anchor)
    step = 1 if ties == "strict" else 0
    cells = []
    for p, (a, b) in enumerate(motif.edges):
        if p in times:
            continue
        before = [F.col(c) for q, c in times.items() if q < p]
        after = [F.col(c) for q, c in times.items() if q > p]
        lo = (F.greatest(*before) if len(before) > 1 else before[0]) + step  # the anchor holds position 0
        hi = F.col(times[0]) + delta
        if after:
            hi = F.least(hi, *[c - step for c in after])
        cells.append(F.struct(F.lit(p).alias("pos"), F.col(where[a]).alias("src"), F.col(where[b]).alias("dst"), lo.alias("lo"), hi.alias("hi")))
    return paths.select("draw", F.inline(F.array(*cells))).where("lo <= hi")


def candidates(tg: TemporalGraph, wanted: DataFrame, delta: int, many: bool = False) -> DataFrame:
    """draw, pos, t: the edges that meet the demands, by an equi-join on pair and time bucket.

    A demand spans at most delta and so at most two buckets; a hot pair is cut by them.
    """
    width = max(1, delta)
    floor = lambda c: f"{c} div {width} - if({c} % {width} < 0, 1, 0)"
    edges = tg.edges.select("src", "dst", "t", F.expr(floor("t")).alias("bucket"))
    spread = wanted.withColumn("bucket", F.explode(F.sequence(F.expr(floor("lo")), F.expr(floor("hi")))))
    return edges.join(spread.hint("merge") if many else spread, ["src", "dst", "bucket"]).where("t between lo and hi").select("draw", "pos", "t")


def chain_fold(items: Column, length: int, start: int = 0) -> Column:
    """Number of increasing chains through positions start..length-1 of an array of (t, order, pos) in scan order."""
    zero = F.array(*[F.lit(0).cast("bigint")] * length)

    def step(acc: Column, x: Column) -> Column:
        return F.transform(acc, lambda c, i: F.when(i == x["pos"], c + F.when(i == start, F.lit(1).cast("bigint")).otherwise(F.get(acc, i - 1))).otherwise(c))

    return F.aggregate(items, zero, step, lambda acc: F.get(acc, F.lit(length - 1)))


def scan_order(ties: str) -> Column:
    """At equal times descending positions make the order strict, ascending ones weak."""
    return -F.col("pos") if ties == "strict" else F.col("pos")


@F.pandas_udf(LongType())
def chain_count(times: pd.Series, positions: pd.Series, length: pd.Series) -> pd.Series:
    """Chains of parallel arrays of times and positions in scan order."""
    out = []
    for ts, ps, n in zip(times, positions, length, strict=True):
        c = [0] * int(n)
        for p in ps[: len(ts)]:
            c[p] += 1 if p == 0 else c[p - 1]
        out.append(c[-1])
    return pd.Series(out, dtype="int64")


@F.pandas_udf(LongType())
def chain_total(times: pd.Series, positions: pd.Series, length: pd.Series) -> int:
    """The same as an aggregate over rows (t, pos, length) in any order; times in a chain increase strictly."""
    n = int(length.iloc[0]) if len(length) else 0
    c = [0] * n
    for p in positions.iloc[np.lexsort((-positions.to_numpy(), times.to_numpy()))].tolist():
        c[p] += 1 if p == 0 else c[p - 1]
    return c[-1] if n else 0


def extend_count(paths: DataFrame, tg: TemporalGraph, motif: Motif, anchor: Anchor, delta: int, ties: str = "strict", impl: str = "fold", many: bool = False) -> DataFrame:
    """draw, x: for each path with at least one completion, how many there are. paths must be valid, draw a key.

    impl: 'fold' (one array per path), 'window' (running sums, nothing gathered), 'arrow' (an Arrow function over the arrays). many: all paths, not a sample; none of them is broadcast.
    """
    length, times = len(motif.edges), anchor_times(anchor)
    if ties != "strict" and len(set(motif.edges)) < length:
        raise ValueError("weak ties would let one edge serve two parallel pattern edges; use an exact counter")
    free = length - len(times)
    if not free:
        return paths.select("draw", F.lit(1).cast("bigint").alias("x"))
    fixed = paths.select("draw", F.inline(F.array(*[F.struct(F.lit(p).alias("pos"), F.col(c).alias("t")) for p, c in times.items()])))
    found = candidates(tg, demands(paths, motif, anchor, delta, ties), delta, many)
    if free == 1:  # bounds already place the edge
        return found.groupBy("draw").agg(F.count(F.lit(1)).alias("x"))
    if impl == "window":
        return _chain_windows(found.unionByName(fixed.select("draw", "pos", "t")), length, ties)
    item = F.struct("t", scan_order(ties).alias("order"), "pos")
    met = found.groupBy("draw").agg(F.collect_list(item).alias("items"), F.collect_set("pos").alias("have")).where(F.size("have") == free)
    ends = paths.select("draw", F.array(*[F.struct(F.col(c).alias("t"), F.lit(-p if ties == "strict" else p).alias("order"), F.lit(p).alias("pos")) for p, c in times.items()]).alias("fixed"))
    rows = met.join(ends.hint("merge") if many else ends, "draw").select("draw", F.array_sort(F.concat("items", "fixed")).alias("items"))
    if impl == "arrow":
        x = chain_count(F.transform("items", lambda i: i["t"]), F.transform("items", lambda i: i["pos"]), F.lit(length))
    else:
        x = chain_fold(F.col("items"), length)
    return rows.select("draw", x.alias("x")).where("x > 0")


def _chain_windows(rows: DataFrame, length: int, ties: str) -> DataFrame:
    rows = rows.withColumn("c", F.when(F.col("pos") == 0, 1).otherwise(0).cast("bigint"))
    before = Window.partitionBy("draw").orderBy("t").rangeBetween(Window.unboundedPreceding, -1 if ties == "strict" else 0)
    for p in range(1, length):
        reach = F.coalesce(F.sum(F.when(F.col("pos") == p - 1, F.col("c"))).over(before), F.lit(0))
        rows = rows.withColumn("c", F.when(F.col("pos") == p, reach).otherwise(F.col("c")))
    return rows.where(F.col("pos") == length - 1).groupBy("draw").agg(F.sum("c").alias("x")).where("x > 0")
