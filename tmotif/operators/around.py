"""Operators around the graph: joins in time, windows, groupings, sets, top lists."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tmotif.operators.prefix import running_in_keys, with_previous
from tmotif.sources.graph import TemporalGraph

#: Width of the time buckets that a vertex's edges are ordered in: a day of microseconds.
BUCKET = 86_400_000_000


def active_centers(weighted: DataFrame) -> DataFrame:
    """Centers with at least one path."""
    return weighted.where("w > 0").select("eid", "src", "dst", "t")


def sources_never_targets(tg: TemporalGraph) -> DataFrame:
    return tg.edges.select(F.col("src").alias("v")).distinct().join(tg.edges.select(F.col("dst").alias("v")), "v", "left_anti")


def _bucketed(tg: TemporalGraph, width: int, *columns: str) -> DataFrame:
    return tg.edges.select(*columns, F.expr(f"t div {width}").alias("bucket"))


def previous_edge(tg: TemporalGraph, by: str = "src", width: int = BUCKET) -> DataFrame:
    """eid, src, t, previous_t: the time of the nearest earlier edge of the same vertex. A hub is ordered in buckets of the width."""
    return with_previous(_bucketed(tg, width, "eid", by, "t"), [by], ["t", "eid"], {"t": "previous_t"})


def edges_per_window(windows: DataFrame, tg: TemporalGraph, width: int) -> DataFrame:
    """win, n from windows (win, a, b) no longer than width, by an equi-join on buckets of that width."""
    from tmotif.operators.baselines import in_windows

    return in_windows(tg, windows, width).groupBy("win").agg(F.count(F.lit(1)).alias("n"))


def tumbling(tg: TemporalGraph, width: int, *by: str) -> DataFrame:
    return tg.edges.groupBy(F.expr(f"t div {width}").alias("bucket"), *by).agg(F.count(F.lit(1)).alias("n"))


def sliding(tg: TemporalGraph, width: int, steps: int) -> DataFrame:
    """bucket, n: edges in the steps buckets of the given width that begin at bucket."""
    at = F.expr(f"t div {width}")
    return tg.edges.select(F.explode(F.sequence(at - (steps - 1), at)).alias("bucket")).groupBy("bucket").agg(F.count(F.lit(1)).alias("n"))


def sessions(tg: TemporalGraph, gap: int, width: int = BUCKET) -> DataFrame:
    """src, t_first, t_last, n: bursts of a vertex's edges less than gap apart (a gap of exactly that begins a new one)."""
    rows = with_previous(_bucketed(tg, width, "eid", "src", "t"), ["src"], ["t", "eid"], {"t": "before"})
    rows = rows.withColumn("new", F.when(F.col("t") - F.col("before") < gap, 0).otherwise(1)).withColumn("bucket", F.expr(f"t div {width}"))
    rows = running_in_keys(rows, ["src"], ["t", "eid"], "new", "k")
    return rows.groupBy("src", "k").agg(F.min("t").alias("t_first"), F.max("t").alias("t_last"), F.count(F.lit(1)).alias("n")).drop("k")


def degrees(tg: TemporalGraph) -> DataFrame:
    """v, degree."""
    return tg.edges.select(F.explode(F.array("src", "dst")).alias("v")).groupBy("v").agg(F.count(F.lit(1)).alias("degree"))


def top_hubs(tg: TemporalGraph, k: int) -> DataFrame:
    return degrees(tg).orderBy(F.desc("degree"), "v").limit(k)


def degree_deciles(tg: TemporalGraph) -> DataFrame:
    """decile, n, low, high over vertices in order of degree; only the histogram (a row for each degree that occurs) is ranked."""
    every = Window.orderBy("degree").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    counts = degrees(tg).groupBy("degree").agg(F.count(F.lit(1)).alias("n"))
    rows = counts.withColumn("end", F.sum("n").over(Window.orderBy("degree").rowsBetween(Window.unboundedPreceding, Window.currentRow))).withColumn("all", F.sum("n").over(every))
    rows = rows.withColumn("start", F.col("end") - F.col("n")).withColumn("tile", F.explode(F.sequence(F.lit(0), F.lit(9))))
    edge = lambda k: k * F.expr("`all` div 10") + F.least(k, F.col("all") % 10)  # noqa: E731  # the first tiles take the rest
    held = F.least("end", edge(F.col("tile") + 1)) - F.greatest("start", edge(F.col("tile")))
    return rows.withColumn("held", held).where("held > 0").groupBy((F.col("tile") + 1).alias("decile")).agg(F.sum("held").alias("n"), F.min("degree").alias("low"), F.max("degree").alias("high"))


def vertex_sets(tg: TemporalGraph) -> DataFrame:
    """kind, n for the union, intersection and difference of sources and targets."""
    s, d = tg.edges.select(F.col("src").alias("v")), tg.edges.select(F.col("dst").alias("v"))
    kinds = {"union": s.union(d).distinct(), "intersect": s.intersect(d), "except": s.subtract(d)}
    out = None
    for k, df in kinds.items():
        one = df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(k).alias("kind"), "n")
        out = one if out is None else out.union(one)
    return out


def gaps(tg: TemporalGraph, width: int = BUCKET) -> DataFrame:
    """eid, gap_before, gap_after: to the nearest earlier and later edge of the same source."""
    rows = with_previous(_bucketed(tg, width, "eid", "src", "t"), ["src"], ["t", "eid"], {"t": "before"})
    rows = with_previous(rows.withColumn("bucket", F.expr(f"t div {width}")), ["src"], ["t", "eid"], {"t": "after"}, back=True)
    return rows.select("eid", (F.col("t") - F.col("before")).alias("gap_before"), (F.col("after") - F.col("t")).alias("gap_after"))


def pair_index(tg: TemporalGraph) -> DataFrame:
    """src, dst, ts: sorted times of each pair. For pairs of bounded multiplicity; joins by bucket need no such arrays."""
    return tg.edges.groupBy("src", "dst").agg(F.array_sort(F.collect_list("t")).alias("ts"))


def times_between(ts: Column, lo: Column, hi: Column) -> Column:
    return F.filter(ts, lambda t: (t >= lo) & (t <= hi))


def pairs_within(small: DataFrame, delta: int) -> DataFrame:
    """All pairs of rows (id, t) at most delta apart, by buckets of delta and their neighbours."""
    width = max(1, delta)
    left = small.select(F.col("id").alias("a"), F.col("t").alias("ta"), F.explode(F.expr(f"sequence(t div {width} - 1, t div {width} + 1)")).alias("bucket"))
    right = small.select(F.col("id").alias("b"), F.col("t").alias("tb"), F.expr(f"t div {width}").alias("bucket"))
    return left.join(right, "bucket").where((F.col("a") < F.col("b")) & (F.abs(F.col("ta") - F.col("tb")) <= delta)).select("a", "b")
