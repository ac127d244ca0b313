"""Other samplers: time windows at uniform starts or at edges, disjoint windows, and edges."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tmotif.functions.motif import motif
from tmotif.operators.exact import _bucket, matches
from tmotif.operators.prefix import counts_below
from tmotif.operators.sampling import BITS, draws
from tmotif.sources.graph import TemporalGraph
from tmotif.sources.io import staged


def _extent(tg: TemporalGraph) -> tuple[int, int, int]:
    row = tg.edges.agg(F.min("t").alias("a"), F.max("t").alias("b"), F.count(F.lit(1)).alias("m")).first()
    return row["a"] or 0, row["b"] or 0, row["m"]


def _row(found: DataFrame, m, delta: int, value) -> DataFrame:
    return found.agg(F.coalesce(F.sum(value), F.lit(0.0)).alias("estimate"), F.count(F.lit(1)).alias("seen")).select(F.lit(m.name).alias("motif"), F.lit(delta).cast("bigint").alias("delta"), "seen", "estimate")


def window_starts(tg: TemporalGraph, delta: int, s: int, c: float, variant: str, seed: int) -> tuple[DataFrame, int]:
    """win, a, b for s windows [a, b] of length c * delta; and how many starts there are to choose from."""
    spark, width = tg.edges.sparkSession, int(c * delta)
    t_min, t_max, m = _extent(tg)
    if variant == "A":
        size = t_max - (t_min - width) + 1
        starts = draws(spark, s, size, seed).select(F.col("draw").alias("win"), (F.col("path_id") + (t_min - width)).cast("bigint").alias("a"))
    else:
        size = m
        from tmotif.operators.prefix import running_total

        numbered = running_total(tg.edges.select("eid", "t"), F.lit(1).cast("bigint"), ["t", "eid"], "number")
        starts = draws(spark, s, size, seed).select(F.col("draw").alias("win"), F.col("path_id").cast("bigint").alias("number")).join(numbered, "number").select("win", F.col("t").alias("a"))
    return starts.withColumn("b", F.col("a") + width), size


def in_windows(tg: TemporalGraph, windows: DataFrame, width: int) -> DataFrame:
    """Edges with the number of each window that holds them, by a bucket of the window length."""
    width = max(1, width)
    spread = windows.withColumn("bucket", F.explode(F.sequence(F.expr(_bucket("a", width)), F.expr(_bucket("b", width)))))
    return tg.edges.withColumn("bucket", F.expr(_bucket("t", width))).join(spread, "bucket").where("t between a and b").select("win", "eid", "src", "dst", "t")


def estimate_windows(tg: TemporalGraph, which, delta: int, s: int, c: float = 1.25, variant: str = "A", seed: int = 42) -> DataFrame:
    """motif, delta, seen, estimate: matches inside s windows, each weighted by the inverse of its chance to be inside one.

    A: starts uniform in time. E: starts at the times of uniformly drawn edges.
    """
    m, width = motif(which), int(c * delta)
    if variant not in ("A", "E"):
        raise ValueError("variant is 'A' or 'E'")
    windows, size = window_starts(tg, delta, s, c, variant, seed)
    found = matches(tg.with_edges(in_windows(tg, windows, width)), m, delta, keys=["win"])
    last = f"t{len(m.edges) - 1}"
    span = F.col(last) - F.col("t0")
    if variant == "A":
        return _row(found, m, delta, F.lit(size / s) / (F.lit(width + 1) - span))
    found = staged(found.select("t0", F.col(last).alias("t_last"), F.monotonically_increasing_id().alias("id")), "found")
    probes = found.select(F.inline(F.array(F.struct(F.lit("lo").alias("slot"), (F.col("t_last") - width).alias("x")), F.struct(F.lit("hi").alias("slot"), (F.col("t0") + 1).alias("x")))), "id").select("x", "slot", "id")
    counts = counts_below(tg.edges.select("t"), probes, [], width).groupBy("id").agg((F.max(F.when(F.col("slot") == "hi", F.col("n"))) - F.max(F.when(F.col("slot") == "lo", F.col("n")))).alias("n"))
    return _row(counts, m, delta, F.lit(size / s) / F.col("n"))


def _chance(seed: int, column) -> object:
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}|"), column.cast("string")).cast("binary")), 1, 13), 16, 10).cast("double") / (1 << BITS)


def estimate_partition(tg: TemporalGraph, which, delta: int, q: float = 0.5, c: float = 4.0, seed: int = 42) -> DataFrame:
    """Disjoint windows of length c * delta from a random shift, each kept with chance q; weight 1 / (q * (1 - span / length))."""
    m, width = motif(which), max(1, int(c * delta))
    shift = int(_shift(tg.edges.sparkSession, seed, width))
    edges = tg.edges.withColumn("win", F.expr(_bucket(f"(t - {shift})", width))).where(_chance(seed, F.col("win")) < q)
    found = matches(tg.with_edges(edges.select("win", "eid", "src", "dst", "t")), m, delta, keys=["win"])
    span = (F.col(f"t{len(m.edges) - 1}") - F.col("t0")).cast("double")
    return _row(found, m, delta, F.lit(1.0) / (q * (1 - span / width)))


def _shift(spark: SparkSession, seed: int, width: int) -> int:
    return draws(spark, 1, width, seed).first()["path_id"]


def estimate_edges(tg: TemporalGraph, which, delta: int, q: float = 0.25, seed: int = 42) -> DataFrame:
    """Edges kept with chance q; matches around each kept edge in every position; weight 1 / (q * edges of the pattern)."""
    m = motif(which)
    kept = tg.edges.where(_chance(seed, F.col("eid")) < q)
    out = None
    for p in range(len(m.edges)):
        one = matches(tg, m, delta, start=p, roots=kept).select(F.lit(1).alias("one"))
        out = one if out is None else out.union(one)
    return _row(out, m, delta, F.lit(1.0 / (q * len(m.edges))))
