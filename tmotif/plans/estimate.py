"""Estimates: sample, check, count completions, scale; and what is built from these."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tmotif.functions.motif import Anchor, Motif, motif
from tmotif.operators import ablation
from tmotif.operators.cycles import cycle_count, is_cycle
from tmotif.operators.dense import dense_counts, fitting, is_dense, leading, may_be_dense
from tmotif.operators.extend import check_paths, extend_count
from tmotif.operators.incidence import ranked_incidence
from tmotif.operators.sampling import list_paths, sample_paths
from tmotif.operators.weights import static_weights, total, weights, with_offsets
from tmotif.sources.graph import TemporalGraph
from tmotif.sources.io import staged

RESULT = "motif string, delta bigint, k bigint, w_total decimal(38,0), cnt decimal(38,0), estimate double, stderr double, ci_lo double, ci_hi double, hit_rate double, valid_rate double"
Z95 = 1.959964


@dataclass
class Prepared:
    """A class's centers with offsets, W, and the graph's ranked lists; shared by all motifs, sample sizes and seeds of that class."""

    tg: TemporalGraph
    delta: int
    cls: object
    centers: DataFrame
    w_total: int
    lists: DataFrame


def prepare(tg: TemporalGraph, delta: int, cls, sampler: str = "centered", buckets: int | None = None, ties: str = "strict", lists: DataFrame | None = None) -> Prepared:
    """Centers and lists are written once to the shared folder: every draw, check and sweep reads them there."""
    weighted = static_weights(tg, cls) if sampler == "static" else weights(tg, delta, cls, ties=ties)
    weighted = staged(weighted.where("w > 0"), "weights")
    centers = staged(with_offsets(weighted, buckets=buckets), "centers")
    return Prepared(tg, delta, cls, centers, total(weighted), staged(ranked_incidence(tg, delta), "lists") if lists is None else lists)


def choose_anchor(tg: TemporalGraph, m: Motif, delta: int, policy="first", k: int = 2_000) -> Anchor:
    """'first', 'min_W' (fewest paths), 'min_WB' (the smallest sample by heuristic_samples, from a pilot of k draws an anchor), or positions."""
    if policy not in ("min_W", "min_WB"):
        return m.anchor(policy)
    m.anchor()
    ready: dict = {}
    for a in m.anchors():
        if a.cls not in ready:
            ready[a.cls] = prepare(tg, delta, a.cls, lists=next((p.lists for p in ready.values()), None)) if policy == "min_WB" else total(weights(tg, delta, a.cls))
    if policy == "min_W":
        return min(m.anchors(), key=lambda a: ready[a.cls])
    # the count is the same for every anchor, so that W times the quantile of completions ranks them
    return min(m.anchors(), key=lambda a: ready[a.cls].w_total * max(pilot(tg, m, delta, k, anchor=a.positions, prepared=ready[a.cls])["b"], 1.0))


def completions(prepared: Prepared, m: Motif, anchor: Anchor, paths: DataFrame, ties: str = "strict", impl: str = "fold", many: bool = False) -> DataFrame:
    """paths with valid and x (0 where nothing completes them)."""
    checked = check_paths(paths, anchor, prepared.delta, ties)
    x = extend_count(checked.where("valid"), prepared.tg, m, anchor, prepared.delta, ties, impl, many)
    return checked.join(x.hint("merge") if many else x, "draw", "left").withColumn("x", F.coalesce("x", F.lit(0).cast("bigint")))


def summary(counted: DataFrame, m: Motif, delta: int, w_total: int, by: list[str] | None = None, k: int | None = None, scheme: str = "iid") -> DataFrame:
    """One row (per group) of RESULT from rows with draw, valid and x; k: draws, if some had no row.

    The standard error is that of the scheme. iid: of a mean of k. without_replacement: of a mean of as many as came back, with the
    correction for a finite population. stratified: from the differences of neighbouring strata, which is
    rather too large. poisson: of a sum of independent draws, which is too large, too, as whole parts are certain.
    """
    n = F.lit(k).cast("bigint") if k else F.count(F.lit(1))
    extra = []
    if scheme == "stratified":
        counted = counted.groupBy(*(by or []), F.expr("draw div 2").alias("pair")).agg(F.sum("x").cast("bigint").alias("x"), F.sum(F.col("x").cast("double") * F.col("x")).alias("own"), F.sum((F.col("x") > 0).cast("double")).alias("hit"), F.sum(F.col("valid").cast("double")).alias("valid"), F.count(F.lit(1)).alias("rows"))
        extra = [F.coalesce(F.sum(2 * F.col("own") - F.col("x").cast("double") * F.col("x")), F.lit(0.0)).alias("apart")]
        squares, hits, n = F.sum("own"), F.sum("hit"), n if k else F.sum("rows")
    else:
        squares, hits = F.sum(F.col("x").cast("double") * F.col("x")), F.sum((F.col("x") > 0).cast("double"))
    rows = counted.groupBy(*(by or [])).agg(
        n.alias("k"),
        F.coalesce(F.sum(F.col("x").cast("decimal(38,0)")), F.lit(0).cast("decimal(38,0)")).alias("cnt"),
        F.coalesce(squares, F.lit(0.0)).alias("squares"),
        F.coalesce(hits, F.lit(0.0)).alias("hits"),
        F.coalesce(F.sum(F.col("valid").cast("double")), F.lit(0.0)).alias("valids"),
        *extra,
    )
    whole, count = float(w_total), F.greatest(F.col("k").cast("double"), F.lit(1.0))
    mean = F.col("cnt").cast("double") / count
    spread = F.greatest(F.col("squares") / count - mean * mean, F.lit(0.0)) / count
    if scheme == "without_replacement":
        spread = spread * F.greatest(1 - count / max(whole, 1.0), F.lit(0.0))
    elif scheme == "poisson":
        spread = F.col("squares") / (count * count)
    elif scheme == "stratified":
        spread = F.greatest(F.col("apart"), F.lit(0.0)) / (count * count)
    rows = rows.withColumn("estimate", mean * whole).withColumn("stderr", whole * F.sqrt(spread))
    return rows.select(
        *(by or []),
        F.lit(m.name).alias("motif"),
        F.lit(delta).cast("bigint").alias("delta"),
        F.col("k").cast("bigint"),
        F.lit(str(w_total)).cast("decimal(38,0)").alias("w_total"),
        "cnt",
        "estimate",
        "stderr",
        (F.col("estimate") - Z95 * F.col("stderr")).alias("ci_lo"),
        (F.col("estimate") + Z95 * F.col("stderr")).alias("ci_hi"),
        (F.col("hits") / count).alias("hit_rate"),
        (F.col("valids") / count).alias("valid_rate"),
    )


def estimate(tg: TemporalGraph, which: str | Motif, delta: int, k: int, seed: int = 42, anchor="first", sampler: str = "centered", scheme: str = "iid", ties: str = "strict", impl: str = "fold", prepared: Prepared | None = None) -> DataFrame:
    """The estimate of one motif's count, one row of RESULT.

    sampler: 'centered' (windowed degrees), 'static' (no time in the weights), 'constrained'
    (order and window among all three anchor edges in the weights), 'hub' (stars).
    W = 0 gives the estimate 0.
    """
    m = motif(which)
    if k <= 0:
        raise ValueError("k is at least 1")
    if sampler == "hub":
        return ablation.hub_estimate(tg, m, delta, k, seed)
    chosen = choose_anchor(tg, m, delta, anchor)
    if sampler == "constrained":
        paths, w_total = ablation.constrained_paths(tg, m, chosen, delta, k, seed)
        prepared = Prepared(tg, delta, chosen.cls, tg.edges, w_total, tg.edges)
    else:
        prepared = prepared or prepare(tg, delta, chosen.cls, sampler, ties=ties)
        w_total = prepared.w_total
        paths = sample_paths(tg, prepared.centers, w_total, delta, chosen.cls, k, seed, scheme, lists=prepared.lists)
    counted = completions(prepared, m, chosen, paths, ties, impl)
    return summary(counted, m, delta, w_total, k=k if scheme in ("iid", "stratified", "poisson") else None, scheme=scheme)


def estimate_seeds(tg: TemporalGraph, which, delta: int, k: int, seeds=range(42, 47), anchor="first", prepared: Prepared | None = None) -> DataFrame:
    """One row per seed (column seed): all draws of all seeds are one sample, extended once."""
    m, seeds = motif(which), [*seeds]
    chosen = choose_anchor(tg, m, delta, anchor)
    prepared = prepared or prepare(tg, delta, chosen.cls)
    paths = sample_paths(tg, prepared.centers, prepared.w_total, delta, chosen.cls, k, seeds, lists=prepared.lists)
    counted = completions(prepared, m, chosen, paths).withColumn("seed", F.get(F.array(*map(F.lit, seeds)), F.expr(f"draw div {k}")))
    rows = summary(counted, m, delta, prepared.w_total, by=["seed"], k=k)
    if prepared.w_total:
        return rows
    none = summary(counted, m, delta, 0, k=k)  # without paths there are no draws: a row of zeros for each seed
    return none.crossJoin(F.broadcast(tg.edges.sparkSession.createDataFrame([(x,) for x in seeds], "seed int"))).select(*rows.columns)


def estimate_many(tg: TemporalGraph, names, delta: int, k: int, seed: int = 42) -> DataFrame:
    """Several motifs: those whose anchors share a class share its weights and its sample, all share the lists."""
    groups: dict = {}
    for name in names:
        m = motif(name)
        groups.setdefault(m.anchor().cls, []).append(m)
    out, lists = None, staged(ranked_incidence(tg, delta), "lists")
    for cls, ms in groups.items():
        prepared = prepare(tg, delta, cls, lists=lists)
        paths = staged(sample_paths(tg, prepared.centers, prepared.w_total, delta, cls, k, seed, lists=lists), "paths")
        for m in ms:
            one = summary(completions(prepared, m, m.anchor(), paths), m, delta, prepared.w_total, k=k)
            out = one if out is None else out.union(one)
    return out


def sweep(tg: TemporalGraph, which, deltas, k: int, seed: int = 42) -> DataFrame:
    """One estimate for each window; ranks don't depend on the window, so that all share the lists."""
    m = motif(which)
    out, lists = None, staged(ranked_incidence(tg, max(deltas)), "lists")
    for d in deltas:
        one = estimate(tg, m, d, k, seed, prepared=prepare(tg, d, m.anchor().cls, lists=lists))
        out = one if out is None else out.union(one)
    return out


def convergence(tg: TemporalGraph, which, delta: int, ks, seeds=range(42, 47), prepared: Prepared | None = None) -> DataFrame:
    """k, seed, estimate, stderr for growing sample sizes, all from one set of weights."""
    m = motif(which)
    prepared = prepared or prepare(tg, delta, m.anchor().cls)
    out = None
    for k in ks:
        one = estimate_seeds(tg, m, delta, k, seeds, prepared=prepared).select("motif", "k", "seed", "cnt", "estimate", "stderr")
        out = one if out is None else out.union(one)
    return out


def pilot(tg: TemporalGraph, which, delta: int, k: int, seed: int = 42, anchor="first", quantile: float = 0.9, prepared: Prepared | None = None) -> dict[str, float]:
    """w, c (the estimated count), b (the quantile of the completions of draws that have any; 0 if none has) and b_max of a small sample."""
    m = motif(which)
    chosen = m.anchor(anchor)
    prepared = prepared or prepare(tg, delta, chosen.cls)
    paths = sample_paths(tg, prepared.centers, prepared.w_total, delta, chosen.cls, k, seed, lists=prepared.lists)
    hit = F.when(F.col("x") > 0, F.col("x"))
    row = completions(prepared, m, chosen, paths).agg(F.sum("x").alias("s"), F.percentile(hit, F.lit(quantile)).alias("b"), F.max("x").alias("m")).first()
    return {"w": float(prepared.w_total), "c": prepared.w_total * float(row["s"] or 0) / k, "b": float(row["b"] or 0), "b_max": float(row["m"] or 0)}


def pilot_samples(tg: TemporalGraph, which, delta: int, k: int = 20_000, seed: int = 42, prepared: Prepared | None = None) -> int | None:
    """heuristic_samples of a pilot; None if no draw of it has a match."""
    got = pilot(tg, which, delta, k, seed, prepared=prepared)
    return heuristic_samples(got["b"], got["w"], got["c"]) if got["c"] else None


def estimate_adaptive(tg: TemporalGraph, which, delta: int, epsilon: float, first: int = 2_000, most: int = 1 << 22, seed: int = 42) -> DataFrame:
    """Doubles k until the 95% half width is at most epsilon of the estimate, or k reaches most. Weights are made once."""
    m = motif(which)
    chosen = m.anchor()
    prepared = prepare(tg, delta, chosen.cls)
    k = first
    while True:
        row = estimate(tg, m, delta, k, seed, prepared=prepared)
        got = row.first()
        if got["estimate"] and (got["ci_hi"] - got["estimate"]) <= epsilon * got["estimate"] or 2 * k > most or not prepared.w_total:
            return row
        k *= 2


def census(tg: TemporalGraph, which, delta: int, anchor="first", ties: str = "strict", impl: str = "fold") -> DataFrame:
    """Exact: the sum of completions over all paths of the anchor's class. One row: motif, delta, w_total, valid_paths, hit_paths, count.

    Where paths are too many to be rows and vertices few (see is_dense), the same numbers come from running sums; one that passes 63 bits is decimal(38,0).
    """
    if dense := census_dense(tg, which, delta, anchor, ties):
        row, w_total, m = dense
        return row.select(F.lit(m.name).alias("motif"), F.lit(delta).cast("bigint").alias("delta"), F.lit(str(w_total)).cast("bigint" if w_total < 1 << 63 else "decimal(38,0)").alias("w_total"), F.col("valid").alias("valid_paths"), F.col("hits").alias("hit_paths"), F.col("found").alias("count"))
    counted, w_total, m = census_rows(tg, which, delta, anchor, ties, impl)
    return counted.agg(
        F.lit(m.name).alias("motif"),
        F.lit(delta).cast("bigint").alias("delta"),
        F.lit(w_total).cast("bigint").alias("w_total"),
        F.coalesce(F.sum(F.col("valid").cast("bigint")), F.lit(0)).cast("bigint").alias("valid_paths"),
        F.coalesce(F.sum((F.col("x") > 0).cast("bigint")), F.lit(0)).cast("bigint").alias("hit_paths"),
        F.coalesce(F.sum("x"), F.lit(0)).cast("bigint").alias("count"),
    )


def census_count(tg: TemporalGraph, which, delta: int) -> DataFrame:
    """One row: motif, delta, count of the census. Cycles of three and four edges in time order are met by wedges around vertices of low degree, so that no path of the anchor is listed, unless the graph is dense (see is_dense)."""
    m = motif(which)
    if is_cycle(m) and not is_dense(tg, m, delta):
        return cycle_count(tg, m, delta).select(F.lit(m.name).alias("motif"), F.lit(delta).cast("bigint").alias("delta"), F.col("count").cast("bigint").alias("count"))
    return census(tg, m, delta).select("motif", "delta", "count")


def census_dense(tg: TemporalGraph, which, delta: int, anchor="first", ties: str = "strict", spread: bool = False) -> tuple[DataFrame, int, Motif] | None:
    """dense_counts (see fitting) with W and the motif; None where paths are to be listed."""
    m = motif(which)
    if anchor != "first" or ties != "strict" or delta < 1 or not may_be_dense(tg, m) or spread and len(m.edges) - leading(m) > 2:
        return None
    w_total = total(weights(tg, delta, m.anchor().cls))
    return (fitting(dense_counts(tg, m, delta, paths=True, spread=spread), "valid", "hits", "found"), w_total, m) if is_dense(tg, m, delta, w_total) else None


def census_rows(tg: TemporalGraph, which, delta: int, anchor="first", ties: str = "strict", impl: str = "fold") -> tuple[DataFrame, int, Motif]:
    m = motif(which)
    chosen = choose_anchor(tg, m, delta, anchor)
    prepared = prepare(tg, delta, chosen.cls, ties=ties)
    paths = list_paths(tg, prepared.centers, delta, chosen.cls, prepared.lists)
    return completions(prepared, m, chosen, paths, ties, impl, many=True), prepared.w_total, m


def required_samples(sigma: float, r: int, w: float, c: float, epsilon: float, gamma: float) -> int:
    """Draws that bound the relative error by epsilon with probability 1 - gamma."""
    if c <= 0 or epsilon <= 0 or not 0 < gamma < 1:
        raise ValueError("the bound needs a positive count and error, and a probability between 0 and 1")
    return math.ceil(3 * sigma**r * w * math.log(2 / gamma) / (c * epsilon**2))


def heuristic_samples(b: float, w: float, c: float) -> int:
    """Draws by a quantile b of the completions of an anchor that has any."""
    if c <= 0:
        raise ValueError("without a match there is no heuristic")
    return math.ceil(b * w / c)
