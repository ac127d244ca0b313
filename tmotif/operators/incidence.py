"""Ranked incidence lists, windowed degrees and multiplicities."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tmotif.functions.motif import PathClass, WedgeClass
from tmotif.operators.prefix import counts_below, ranked
from tmotif.sources.graph import TemporalGraph


#: A vertex's edges are ordered in buckets of so small a part of the window, so that a dense hub is many tasks even within one.
PARTS = 8


def ranked_incidence(tg: TemporalGraph, delta: int) -> DataFrame:
    """dir, vertex, rank, t, eid, other: each vertex's out- ('+') and in-list ('-') in (t, eid) order."""
    return ranked(tg.both_roles(), ["dir", "vertex"], ["t", "eid"], delta // PARTS)


def window_bounds(t: Column, side: str, delta: int, ties: str = "strict") -> tuple[Column, Column]:
    """(x, y): an edge at time s is in the window if x <= s < y."""
    if ties in ("closed", "weak"):
        return (t - delta, t + 1) if side == "<" else (t, t + delta + 1)
    return (t - delta, t) if side == "<" else (t + 1, t + delta + 1)


def class_ends(cls: PathClass | WedgeClass) -> list[tuple[str, str, str, str]]:
    """(number, column of the end vertex, sign, side) of each end edge."""
    if isinstance(cls, PathClass):
        return [("1", "src", cls.a1, cls.b1), ("3", "dst", cls.a3, cls.b3)]
    return [("1", cls.pivot, cls.a, cls.b)]


def windowed_degrees(tg: TemporalGraph, delta: int, cls: PathClass | WedgeClass, impl: str = "sweep", ties: str = "strict") -> DataFrame:
    """Edges with lo1, n1 (and lo3, n3): first rank and number of the end edges of the class within the window.

    sweep: probes and list entries in one sort and one running count. frame: a
    range frame over the lists (n only, for cross-checks). closed ties count
    edges at the center's own time, but never the center itself; weak ones count
    that too, so that ranks stay gapless (it fails the check of distinct vertices).
    """
    edges = tg.edges.select("eid", "src", "dst", "t")
    ends = class_ends(cls)
    if impl == "frame":
        return _framed(edges, delta, ends)
    lists = tg.both_roles().select("dir", "vertex", "t")
    probes = None
    for k, end, sign, side in ends:
        x, y = window_bounds(F.col("t"), side, delta, ties)
        rows = edges.select(F.lit(sign).alias("dir"), F.col(end).alias("vertex"), F.inline(F.array(F.struct(F.lit(f"lo{k}").alias("slot"), x.alias("x")), F.struct(F.lit(f"hi{k}").alias("slot"), y.alias("x")))), "eid")
        probes = rows if probes is None else probes.union(rows)
    probes = probes.select("dir", "vertex", "x", "slot", "eid")
    needed = lists.where(F.col("dir").isin(*{sign for _, _, sign, _ in ends}))
    counts = counts_below(needed, probes, ["dir", "vertex"], delta // PARTS).groupBy("eid").agg(*[F.max(F.when(F.col("slot") == f"{w}{k}", F.col("n"))).alias(f"{w}{k}") for k, *_ in ends for w in ("lo", "hi")])
    out = edges.join(counts, "eid")
    for k, end, sign, _ in ends:
        itself = 1 if ties == "closed" and (end, sign) in (("src", "+"), ("dst", "-")) else 0
        out = out.withColumn(f"n{k}", F.col(f"hi{k}") - F.col(f"lo{k}") - itself).drop(f"hi{k}")
    return out.select("eid", "src", "dst", "t", *[f"{w}{k}" for k, *_ in ends for w in ("lo", "n")])


def _framed(edges: DataFrame, delta: int, ends) -> DataFrame:
    out = edges
    for k, end, sign, side in ends:
        entries = edges.select(F.col("src" if sign == "+" else "dst").alias("vertex"), "t", F.lit(1).alias("one"), F.lit(None).cast("bigint").alias("eid"))
        probes = edges.select(F.col(end).alias("vertex"), "t", F.lit(0).alias("one"), "eid")
        frame = Window.partitionBy("vertex").orderBy("t").rangeBetween(*((-delta, -1) if side == "<" else (1, delta)))
        n = entries.union(probes).withColumn(f"n{k}", F.coalesce(F.sum("one").over(frame), F.lit(0)).cast("bigint")).where("one = 0")
        out = out.join(n.select("eid", f"n{k}"), "eid")
    return out


def multiplicity(tg: TemporalGraph, delta: int) -> DataFrame:
    """One row: sigma and sigma_avg, the largest and the mean number of edges of one pair within [t, t + delta] of an edge at t.

    Two probes an edge into the running count of its pair, so that a hot pair costs no square.
    """
    edges = tg.edges.select("eid", "src", "dst", "t")
    cells = F.array(F.struct(F.lit("lo").alias("slot"), F.col("t").alias("x")), F.struct(F.lit("hi").alias("slot"), (F.col("t") + delta + 1).alias("x")))
    probes = edges.select("src", "dst", "eid", F.inline(cells)).select("src", "dst", "x", "slot", "eid")
    counts = counts_below(edges.select("src", "dst", "t"), probes, ["src", "dst"], delta // PARTS).groupBy("eid").agg((F.max(F.when(F.col("slot") == "hi", F.col("n"))) - F.max(F.when(F.col("slot") == "lo", F.col("n")))).alias("m"))
    return counts.agg(F.max("m").alias("sigma"), F.avg("m").alias("sigma_avg"))
