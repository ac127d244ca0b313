"""Accuracy and cost measures."""

from __future__ import annotations

import math
import threading
import time
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tmotif.functions.motif import motif
from tmotif.operators.dense import fitting
from tmotif.operators.exact import listed
from tmotif.operators.weights import total, weights
from tmotif.plans.estimate import census, census_dense, census_rows, estimate, estimate_seeds
from tmotif.sources.graph import TemporalGraph


def anchor_stats(tg: TemporalGraph, which, delta: int) -> DataFrame:
    """motif, b_max, b_avg and b_std over anchors with a match, b_avg_all over all paths, and the counts behind these.

    Where a graph is not dense the matches are listed, not the paths, which are far more: those of one anchor are its completions.
    """
    if dense := census_dense(tg, which, delta, spread=True):
        row, w_total, m = dense
        hits, found, squares = (F.when(F.col("hits") > 0, F.col(c)).cast("double") for c in ("hits", "found", "squares"))
        apart = F.sqrt(F.greatest(squares / hits - found / hits * (found / hits), F.lit(0.0)))
        return row.select(F.lit(m.name).alias("motif"), F.col("most").alias("b_max"), F.col("hits"), F.col("found").alias("count"), (found / hits).alias("b_avg"), apart.alias("b_std"), (F.col("found").cast("double") / F.lit(float(max(w_total, 1)))).alias("b_avg_all"))
    m = motif(which)
    anchor = m.anchor()
    w_total = total(weights(tg, delta, anchor.cls))
    counted = listed(tg, m, delta).groupBy(*[f"e{p}" for p in anchor.positions]).agg(F.count(F.lit(1)).alias("x"))
    hit = F.col("x")
    return counted.agg(F.lit(m.name).alias("motif"), F.coalesce(F.max("x"), F.lit(0)).cast("bigint").alias("b_max"), F.count(hit).alias("hits"), F.coalesce(F.sum("x"), F.lit(0)).cast("bigint").alias("count"), F.avg(hit).alias("b_avg"), F.stddev_pop(hit).alias("b_std"), (F.coalesce(F.sum("x"), F.when(F.lit(w_total > 0), F.lit(0))) / F.lit(float(max(w_total, 1)))).alias("b_avg_all"))


def b_quantile(tg: TemporalGraph, which, delta: int, q: float = 0.9) -> float:
    counted, _, _ = census_rows(tg, which, delta)
    return counted.where("x > 0").agg(F.percentile("x", F.lit(q))).first()[0] or 0.0


def accuracy(tg: TemporalGraph, which, delta: int, k: int, seeds=range(42, 47)) -> DataFrame:
    """motif, exact, mean_error, std_error of the relative error over seeded runs."""
    exact = census(tg, which, delta).select(F.col("count").alias("exact"))
    runs = estimate_seeds(tg, which, delta, k, seeds).select("motif", "estimate").crossJoin(F.broadcast(exact))  # one row
    error = F.when(F.col("exact") > 0, F.abs(F.col("estimate") - F.col("exact")) / F.col("exact"))
    return runs.groupBy("motif", "exact").agg(F.avg(error).alias("mean_error"), F.coalesce(F.stddev_samp(error), F.lit(0.0)).alias("std_error"))


def hit_rates(tg: TemporalGraph, which, delta: int, k: int, seed: int = 42, samplers=("static", "centered", "constrained")) -> DataFrame:
    """sampler, w_total, valid_rate, hit_rate."""
    out = None
    for s in samplers:
        one = estimate(tg, which, delta, k, seed, sampler=s).select(F.lit(s).alias("sampler"), "w_total", "valid_rate", "hit_rate")
        out = one if out is None else out.union(one)
    return out


def count_table(graphs: dict[str, tuple[TemporalGraph, int]], names) -> DataFrame:
    """graph, motif, count by census, with rollup totals (null: all); decimal(38,0) where one passes 63 bits."""
    out = None
    for g, (tg, delta) in graphs.items():
        for name in names:
            one = census(tg, name, delta).select(F.lit(g).alias("graph"), "motif", "count")
            out = one if out is None else out.union(one)
    return fitting(out.rollup("graph", "motif").agg(F.sum(F.col("count").cast("decimal(38,0)")).alias("count")), "count")


def count_ratios(tg: TemporalGraph, delta: int, pairs) -> DataFrame:
    """above, below, counts and their ratio."""
    rows = None
    for a, b in pairs:
        x, y = census(tg, a, delta).select(F.col("motif").alias("above"), F.col("count").alias("above_count")), census(tg, b, delta).select(F.col("motif").alias("below"), F.col("count").alias("below_count"))
        one = x.crossJoin(y).withColumn("ratio", F.when(F.col("below_count") > 0, F.col("above_count").cast("double") / F.col("below_count").cast("double")))
        rows = one if rows is None else rows.union(one)
    return rows


def relative_error(estimate_: float, exact: float) -> float | None:
    """None where there is nothing to be found."""
    return abs(exact - estimate_) / exact if exact else None


def speedup(baseline: list[float], ours: list[float]) -> tuple[list[float], float]:
    """Baseline time over ours, and the geometric mean."""
    each = [a / b for a, b in zip(baseline, ours, strict=True)]
    return each, math.exp(sum(map(math.log, each)) / len(each)) if each else float("nan")


def heuristic_seconds(b_high: float, b_avg: float, w: float, c: float, seconds_per_step: float) -> float:
    """Time that grows with the product of sample size and mean work per draw."""
    return b_high * b_avg * w / c * seconds_per_step


def guarded(spark: SparkSession, run: Callable[[], object], seconds: float) -> tuple[str, float, object]:
    """('ok', 'timeout' or 'memory'; seconds taken; the result or None) of a run of Spark jobs that is ended after so many seconds."""
    context, group = spark.sparkContext, f"guarded-{uuid.uuid4().hex}"
    late = threading.Event()

    def end() -> None:
        late.set()
        while not done.wait(0.2):  # jobs that the run starts after the first are ended, too
            context.cancelJobGroup(group)

    done, timer, began = threading.Event(), threading.Timer(seconds, end), time.time()
    context.setJobGroup(group, group, True)
    timer.start()
    try:
        value = run()
        return "ok", time.time() - began, value
    except Exception as error:  # noqa: BLE001
        if late.is_set():
            return "timeout", time.time() - began, None
        if "OutOfMemory" in str(error):
            return "memory", time.time() - began, None
        raise
    finally:
        done.set()
        timer.cancel()
        for key in ("spark.jobGroup.id", "spark.job.description", "spark.job.interruptOnCancel"):
            context.setLocalProperty(key, None)


def table_bytes(df: DataFrame) -> int:
    """Catalyst's estimate of the bytes of a table or an operator's result."""
    return int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes().toString())

