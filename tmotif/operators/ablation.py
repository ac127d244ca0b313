"""Other samplers: weights under the full constraints of an anchor, and hubs of stars."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tmotif.functions.motif import Anchor, Motif, PathClass
from tmotif.operators.incidence import ranked_incidence, window_bounds
from tmotif.operators.prefix import counts_below
from tmotif.operators.sampling import draws, locate
from tmotif.operators.weights import total, weights, with_offsets
from tmotif.sources.graph import TemporalGraph
from tmotif.sources.io import staged


def _third_window(anchor: Anchor, delta: int):
    """(x, y): times s of edge 3 with x <= s < y given t (center) and t1, under pattern order and window."""
    one, center, three = anchor.positions
    times = {one: F.col("t1"), center: F.col("t")}
    early, late = F.least("t1", "t"), F.greatest("t1", "t")
    before, after = [c for p, c in times.items() if p < three], [c for p, c in times.items() if p > three]
    x = reduce(F.greatest, [c + 1 for c in before], late - delta)
    y = reduce(F.least, after, early + delta + 1)
    return x, F.greatest(x, y)


def constrained_weights(tg: TemporalGraph, anchor: Anchor, delta: int) -> DataFrame:
    """A row for each (center, edge 1) in order and window: eid, src, dst, t, eid1, t1, v0, lo3, n3, w = n3."""
    cls: PathClass = anchor.cls
    one, center, _ = anchor.positions
    lists = ranked_incidence(tg, delta)
    centers = weights(tg, delta, cls).where("n1 > 0").withColumn("rank", F.explode(F.expr("sequence(lo1, lo1 + n1 - 1)")))
    ends = lists.where(F.col("dir") == cls.a1).select(F.col("vertex").alias("src"), "rank", F.col("t").alias("t1"), F.col("eid").alias("eid1"), F.col("other").alias("v0"))
    pairs = centers.select("eid", "src", "dst", "t", "rank").join(ends, ["src", "rank"]).drop("rank")
    x, y = _third_window(anchor, delta)
    pairs = pairs.withColumn("x", x).withColumn("y", y).where("x < y")
    probes = pairs.select(F.lit(cls.a3).alias("dir"), F.col("dst").alias("vertex"), F.inline(F.array(F.struct(F.lit("lo").alias("slot"), F.col("x").alias("x")), F.struct(F.lit("hi").alias("slot"), F.col("y").alias("x")))), "eid", "eid1").select("dir", "vertex", "x", "slot", "eid", "eid1")
    data = tg.both_roles().where(F.col("dir") == cls.a3).select("dir", "vertex", "t")
    counts = counts_below(data, probes, ["dir", "vertex"], delta).groupBy("eid", "eid1").agg(F.max(F.when(F.col("slot") == "lo", F.col("n"))).alias("lo3"), F.max(F.when(F.col("slot") == "hi", F.col("n"))).alias("hi3"))
    return pairs.drop("x", "y").join(counts, ["eid", "eid1"]).withColumn("n3", F.col("hi3") - F.col("lo3")).withColumn("w", F.col("n3")).drop("hi3")


def constrained_paths(tg: TemporalGraph, motif: Motif, anchor: Anchor, delta: int, k: int, seed: int = 42) -> tuple[DataFrame, int]:
    """k paths drawn uniformly from those in pattern order and window, and how many there are. For paths."""
    if len(anchor.positions) != 3:
        raise ValueError("constrained sampling is for four vertices")
    pairs = staged(constrained_weights(tg, anchor, delta).where("w > 0"), "pairs")
    w_total = total(pairs)
    found = locate(draws(tg.edges.sparkSession, k, w_total, seed), staged(with_offsets(pairs, ["t", "eid", "eid1"]), "centers"), k)
    ends = ranked_incidence(tg, delta).where(F.col("dir") == anchor.cls.a3).select(F.col("vertex").alias("dst"), "rank", F.col("t").alias("t3"), F.col("eid").alias("eid3"), F.col("other").alias("v3"))
    out = found.withColumn("rank", F.col("lo3") + F.col("o")).join(ends, ["dst", "rank"])
    return out.select("draw", "path_id", "eid1", F.col("eid").alias("eid2"), "eid3", "t1", F.col("t").alias("t2"), "t3", "v0", F.col("src").alias("v1"), F.col("dst").alias("v2"), "v3"), w_total


def hub_estimate(tg: TemporalGraph, motif: Motif, delta: int, k: int, seed: int = 42) -> DataFrame:
    """Stars of three leaves: edge 0 is the base, its hub's later edges give two windowed degrees, a draw is one pair of these."""
    from tmotif.operators.extend import _all
    from tmotif.plans.estimate import summary

    hubs = set.intersection(*map(set, motif.edges))
    if len(motif.edges) != 3 or len(hubs) != 1:
        raise ValueError("the hub sampler is for stars of three edges")
    hub = hubs.pop()
    signs = ["+" if a == hub else "-" for a, _ in motif.edges]
    base = tg.edges.select("eid", F.col("src" if signs[0] == "+" else "dst").alias("hub"), F.col("dst" if signs[0] == "+" else "src").alias("leaf0"), "t")
    x, y = window_bounds(F.col("t"), ">", delta)
    data = tg.both_roles().select("dir", "vertex", "t")
    slots = [F.struct(F.lit(s).alias("dir"), F.lit(f"{w}{s}").alias("slot"), c.alias("x")) for s in sorted({*signs[1:]}) for w, c in (("lo", x), ("hi", y))]
    probes = base.select(F.col("hub").alias("vertex"), "eid", F.inline(F.array(*slots))).select("dir", "vertex", "x", "slot", "eid")
    counts = counts_below(data, probes, ["dir", "vertex"], delta).groupBy("eid").agg(*[F.max(F.when(F.col("slot") == f"{w}{s}", F.col("n"))).alias(f"{w}{s}") for s in sorted({*signs[1:]}) for w in ("lo", "hi")])
    rows = base.join(counts, "eid")
    for i in (1, 2):
        rows = rows.withColumn(f"lo{i}", F.col(f"lo{signs[i]}")).withColumn(f"n{i}", F.col(f"hi{signs[i]}") - F.col(f"lo{signs[i]}"))
    rows = rows.select("eid", "hub", "leaf0", "t", "lo1", "n1", "lo2", "n2", (F.col("n1") * F.col("n2")).alias("w"))
    rows = staged(rows.where("w > 0"), "hubs")
    w_total = total(rows)
    found = locate(draws(tg.edges.sparkSession, k, w_total, seed), staged(with_offsets(rows), "centers"), k)
    found = found.withColumn("r1", F.expr("lo1 + o div n2")).withColumn("r2", F.expr("lo2 + o % n2"))
    lists = ranked_incidence(tg, delta)
    for i in (1, 2):
        own = lists.where(F.col("dir") == signs[i]).select(F.col("vertex").alias("hub"), F.col("rank").alias(f"r{i}"), F.col("t").alias(f"t{i}"), F.col("other").alias(f"leaf{i}"))
        found = found.join(own, ["hub", f"r{i}"])
    apart = _all([F.col(f"leaf{i}") != F.col(f"leaf{j}") for i in range(3) for j in range(i)])
    valid = apart & (F.col("t1") < F.col("t2"))
    return summary(found.select("draw", valid.alias("valid"), valid.cast("bigint").alias("x")), motif, delta, w_total, k=k)
