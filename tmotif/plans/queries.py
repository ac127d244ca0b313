"""The driver's queries: every method, variant, baseline and measure on edge views of the given tables."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from functools import partial, reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tmotif.functions.motif import CATALOG, EIGHT, PathClass, WedgeClass
from tmotif.operators import around, baselines, exact, incidence, measures, sampling, weights
from tmotif.operators.ablation import constrained_weights
from tmotif.operators.cycles import is_cycle
from tmotif.operators.extend import check_paths
from tmotif.plans import estimate as plans
from tmotif.plans.oracles import ANCHORS, BOUNDS, CENSUS, DAY, ERRORS, EXACT, F_DELTA, GROWING, HEURISTIC, HOUR, K, LABELS, N_DELTA, PILOT, R_DELTA, RATIOS, SEEDS, T_DELTA, TABLE, WINDOWS, WORKLOADS
from tmotif.sources import graph
from tmotif.sources.graph import TemporalGraph
from tmotif.sources.io import staged, workspace
from tmotif.streaming import streams

THROUGH = PathClass("-", "+", "<", ">")
WEDGE = WedgeClass("dst", "+", ">")
VIEWS = {"R": graph.reply_graph, "F": partial(graph.reply_graph, fold=6), "N": graph.nation_graph, "T": graph.trade_graph, "T2": partial(graph.trade_graph, numbered=False)}


def view(spark: SparkSession, sf_dir: str, name: str) -> TemporalGraph:
    """An edge view, written once for the many passes of a query."""
    return VIEWS[name](spark, sf_dir).staged()


def _on(name: str, function: Callable[[TemporalGraph], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, sf_dir: function(view(spark, sf_dir, name))


def _integers(row: DataFrame) -> DataFrame:
    return row.select("motif", "delta", "k", F.col("w_total").cast("bigint").alias("w_total"), F.col("cnt").cast("bigint").alias("cnt"), "estimate")


def _rounded(row: DataFrame) -> DataFrame:
    return row.select("motif", "delta", "seen", F.round("estimate").cast("bigint").alias("estimate"))


def _offset_paths(tg: TemporalGraph, cls, k: int | None = None) -> DataFrame:
    prepared = plans.prepare(tg, R_DELTA, cls)
    paths = sampling.sample_paths(tg, prepared.centers, prepared.w_total, R_DELTA, cls, k) if k else sampling.list_paths(tg, prepared.centers, R_DELTA, cls)
    return paths.withColumn("path_id", F.col("path_id").cast("bigint"))


def _closed_vs_strict(tg: TemporalGraph) -> DataFrame:
    cls = PathClass("-", "-", "<", "<")
    strict = incidence.windowed_degrees(tg, N_DELTA, cls).agg(F.sum("n1").alias("strict"))
    closed = incidence.windowed_degrees(tg, N_DELTA, cls, ties="closed").agg(F.sum("n1").alias("closed"))
    return strict.crossJoin(closed)  # two single rows


def _chains(tg: TemporalGraph, delta: int) -> DataFrame:
    """Pairs of an edge and a later one the other way, strictly and weakly later."""
    width = max(1, delta)
    a = tg.edges.select("src", "dst", F.col("t").alias("lo"), F.explode(F.expr(f"sequence(t div {width}, (t + {delta}) div {width})")).alias("bucket"))
    b = tg.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "t", F.expr(f"t div {width}").alias("bucket"))
    met = a.join(b, ["src", "dst", "bucket"]).where(F.col("t").between(F.col("lo"), F.col("lo") + delta))
    return met.agg(F.coalesce(F.sum((F.col("t") > F.col("lo")).cast("bigint")), F.lit(0)).cast("bigint").alias("strict"), F.count(F.lit(1)).alias("weak"))


def _windows_of_days(tg: TemporalGraph) -> DataFrame:
    start = tg.edges.agg(F.min("t").alias("start"))
    spark = tg.edges.sparkSession
    wins = spark.range(30).crossJoin(F.broadcast(start)).select(F.col("id").alias("win"), (F.col("start") + F.col("id") * DAY).alias("a"))  # one row
    return around.edges_per_window(wins.withColumn("b", F.col("a") + DAY // 2), tg, DAY // 2)


def _regions(spark: SparkSession, sf_dir: str) -> DataFrame:
    nation = graph.table(spark, sf_dir, "nation").join(graph.table(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_nationkey").cast("bigint").alias("k"), "r_name")
    edges = view(spark, sf_dir, "N").edges
    named = edges.join(nation.select(F.col("k").alias("src"), F.col("r_name").alias("from_region")), "src").join(nation.select(F.col("k").alias("dst"), F.col("r_name").alias("to_region")), "dst")
    return named.groupingSets([["from_region"], ["to_region"], ["from_region", "to_region"]], "from_region", "to_region").agg(F.count(F.lit(1)).alias("n"))


def _calendar(tg: TemporalGraph) -> DataFrame:
    day = F.date_from_unix_date(F.col("t").cast("int"))
    return tg.edges.select(F.year(day).alias("year"), F.month(day).alias("month")).rollup("year", "month").agg(F.count(F.lit(1)).alias("n"))


def _topics(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graph.table(spark, sf_dir, "events").groupBy(F.get_json_object("props", "$.k").cast("int").alias("topic")).agg(F.count(F.lit(1)).alias("n"))


def _streamed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Daily counts by type, through a stream of the events file (a glob, so that a file or a folder will do); complete mode needs no last watermark."""
    table = graph.table(spark, sf_dir, "events")
    rows = spark.readStream.schema(table.schema).parquet(f"{sf_dir}/events.parque[t]").select(F.col("ts").cast("timestamp").alias("ts"), "event_type")
    kept: list[DataFrame] = []
    query = streams.stream_tumbling(rows, "1 day", "event_type").writeStream.outputMode("complete").foreachBatch(lambda df, _: kept.append(staged(df, "tumbling"))).option("checkpointLocation", f"{workspace(spark)}/log-{uuid.uuid4().hex}").trigger(availableNow=True).start()
    query.awaitTermination()
    return kept[-1].select(F.unix_date(F.to_date("start")).cast("bigint").alias("day"), "event_type", "n")


def _bounds(tg: TemporalGraph) -> DataFrame:
    """Draws by the bound, from the multiplicity, the paths and the count of the graph itself; null where there is no match."""
    sigma = incidence.multiplicity(tg, F_DELTA).first()["sigma"]
    rows = []
    for n in BOUNDS:
        w, c = weights.total(weights.weights(tg, F_DELTA, CATALOG[n].anchor().cls)), int(plans.census(tg, n, F_DELTA).first()["count"])
        rows.append((n, plans.required_samples(sigma, CATALOG[n].free_edges, w, c, 0.1, 0.05) if c else None))
    return tg.edges.sparkSession.createDataFrame(rows, "motif string, k bigint")


def _approximate(tg: TemporalGraph) -> DataFrame:
    """Vertices, and whether the sketch is within three of its standard errors (5 % each)."""
    exact_row = tg.vertices().agg(F.count(F.lit(1)).alias("exact"))
    both = tg.approximate_vertices().crossJoin(exact_row)  # two single rows
    return both.select(F.col("exact").alias("vertices"), (F.abs(F.col("vertices") - F.col("exact")) <= 0.15 * F.col("exact")).alias("near"))


def _union(rows) -> DataFrame:
    return reduce(DataFrame.unionByName, rows)


def _counts(tg: TemporalGraph, names, delta: int) -> DataFrame:
    """Counts alone, so that no path of an anchor is listed: cycles by wedges, the others by joins that close what they can first."""
    return _union(plans.census_count(tg, n, delta) if is_cycle(CATALOG[n]) else exact.exact_frontier(tg, n, delta) for n in names)


def _anchors(spark: SparkSession, sf_dir: str) -> DataFrame:
    graphs = {v: view(spark, sf_dir, v) for v in {v for v, _, _ in ANCHORS}}
    rows = _union(measures.anchor_stats(graphs[v], n, delta).withColumn("graph", F.lit(v)) for v, n, delta in ANCHORS)
    return rows.select("graph", "motif", "b_max", "hits", "count", F.round("b_avg", 6).alias("b_avg"), F.round("b_std", 6).alias("b_std"), F.round("b_avg_all", 9).alias("b_avg_all"))


def _errors(tg: TemporalGraph) -> DataFrame:
    rows = _union(measures.accuracy(tg, n, F_DELTA, K, SEEDS) for n in ERRORS)
    return rows.select("motif", "exact", F.round("mean_error", 6).alias("mean_error"), F.round("std_error", 6).alias("std_error"))


def _pilots(tg: TemporalGraph) -> DataFrame:
    rows = [(n, plans.pilot_samples(tg, n, F_DELTA, PILOT)) for n in HEURISTIC]
    return tg.edges.sparkSession.createDataFrame(rows, "motif string, k bigint")


def _ratios(tg: TemporalGraph) -> DataFrame:
    """Of motifs, and of one motif in the multigraph and in the graph of each pair's first edges."""
    rows = measures.count_ratios(tg, F_DELTA, RATIOS).drop("ratio")
    few = plans.census(tg.simple(), "TRI", F_DELTA).select(F.lit("TRI-simple").alias("below"), F.col("count").alias("below_count"))
    one = plans.census(tg, "TRI", F_DELTA).select(F.col("motif").alias("above"), F.col("count").alias("above_count")).crossJoin(few)  # two single rows
    return _union([rows, one])


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The estimate of M4-0 with 20,000 draws, beside the census."""
    tg = view(spark, sf_dir, "R")
    row = plans.estimate(tg, "M4-0", 2 * DAY, 20_000)
    return row.crossJoin(plans.census(tg, "M4-0", 2 * DAY).select(F.col("count").alias("exact")))  # two single rows


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    out: dict[str, Callable[[SparkSession, str], DataFrame]] = {
        "edges_reply": lambda s, d: graph.reply_graph(s, d).edges,
        "edges_folded": lambda s, d: graph.reply_graph(s, d, 6).edges,
        "edges_nation": lambda s, d: graph.nation_graph(s, d).edges,
        "edges_trade": lambda s, d: graph.trade_graph(s, d).edges,
        "graph_profile": _on("R", lambda g: g.profile()),
        "static_edges": _on("R", lambda g: g.static_edges()),
        "edge_self_loops": lambda s, d: graph.reply_graph(s, d, 6, keep_loops=True).edges.where("src = dst").agg(F.count(F.lit(1)).alias("loops")),
        "approx_vertices": _on("R", _approximate),
        "ranked_out": _on("R", lambda g: incidence.ranked_incidence(g, R_DELTA).where("dir = '+'").select("vertex", "rank", "t", "eid", "other")),
        "ranked_in": _on("R", lambda g: incidence.ranked_incidence(g, R_DELTA).where("dir = '-'").select("vertex", "rank", "t", "eid", "other")),
        "degrees_before_in": _on("R", lambda g: incidence.windowed_degrees(g, R_DELTA, THROUGH).select("eid", "lo1", "n1")),
        "degrees_after_out": _on("R", lambda g: incidence.windowed_degrees(g, R_DELTA, THROUGH).select("eid", "lo3", "n3")),
        "degree_closed_vs_strict": _on("N", _closed_vs_strict),
        "multiplicity_max": _on("F", lambda g: incidence.multiplicity(g, F_DELTA).select("sigma")),
        "path_weights_16": _on("R", lambda g: weights.all_weights(g, R_DELTA)),
        "path_totals": _on("R", lambda g: weights.totals(g, R_DELTA)),
        "wedge_totals": _on("R", lambda g: weights.totals(g, R_DELTA, WedgeClass.all())),
        "path_probabilities": _on("R", lambda g: weights.probabilities(weights.weights(g, R_DELTA, THROUGH)).select("eid", "w", "p")),
        "weights_static": _on("R", lambda g: weights.static_weights(g, THROUGH).select("eid", "n1", "n3", "w")),
        "weights_constrained": _on("R", lambda g: constrained_weights(g, CATALOG["M4-0"].anchor(), R_DELTA).select("eid", "eid1", "w")),
        "wedges_listed": _on("R", lambda g: _offset_paths(g, WEDGE).select("eid1", "eid2", "v0", "v1", "v2")),
        "paths_listed": _on("R", lambda g: _offset_paths(g, THROUGH).select("eid1", "eid2", "eid3")),
        "path_ids_bijection": _on("R", lambda g: _offset_paths(g, THROUGH).groupBy("eid1", "eid2", "eid3").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("path_id").alias("d")).agg(F.sum("n").alias("ids"), F.sum("d").alias("distinct_ids"), F.count(F.lit(1)).alias("distinct_paths"))),
        "sample_paths_md5": _on("R", lambda g: _offset_paths(g, THROUGH, K)),
        "sample_wedges_md5": _on("R", lambda g: _offset_paths(g, WEDGE, K)),
        "path_check_flags": _on("R", lambda g: check_paths(_offset_paths(g, THROUGH, K), CATALOG["M4-0"].anchor(), R_DELTA).select("draw", "valid")),
        "star_exact": _on("R", lambda g: exact.exact_backtrack(g, "STAR", R_DELTA)),
        "matches_listed": _on("F", lambda g: exact.matches(g, "TRI", F_DELTA).select(F.col("e0").alias("eid0"), F.col("e1").alias("eid1"), F.col("e2").alias("eid2"), F.col("t0").alias("t_first"), F.col("t2").alias("t_last"))),
        "chain_count_two_lists": _on("F", lambda g: _chains(g, F_DELTA).select(F.col("strict").alias("chains"))),
        "chain_count_ties": _on("N", lambda g: _chains(g, N_DELTA)),
        "backtrack_bucketed_m4_0": _on("F", lambda g: exact.exact_bucketed(g, "M4-0", F_DELTA)),
        "census_bipartite_tri": _on("T2", lambda g: plans.census_count(g, "TRI", T_DELTA)),
        "bipartite_cycle": _on("T2", lambda g: plans.census_count(g, "M4-0", T_DELTA)),
        "nation_ties_tri": _on("N", lambda g: plans.census(g, "TRI", N_DELTA).select("motif", "delta", "count")),
        "estimate_static": _on("R", lambda g: _integers(plans.estimate(g, "M4-0", R_DELTA, K, sampler="static"))),
        "estimate_constrained": _on("R", lambda g: _integers(plans.estimate(g, "M4-0", R_DELTA, K, sampler="constrained"))),
        "estimate_hub_star": _on("R", lambda g: _integers(plans.estimate(g, "STAR", R_DELTA, K, sampler="hub"))),
        "estimate_adaptive": _on("F", lambda g: _integers(plans.estimate_adaptive(g, "M4-0", F_DELTA, 0.1))),
        "estimate_stratified": _on("F", lambda g: _integers(plans.estimate(g, "M4-0", F_DELTA, K, scheme="stratified"))),
        "estimate_without_replacement": _on("F", lambda g: _integers(plans.estimate(g, "M4-0", F_DELTA, K, scheme="without_replacement"))),
        "estimate_poisson": _on("F", lambda g: _integers(plans.estimate(g, "M4-0", F_DELTA, K, scheme="poisson"))),
        "estimate_eight": _on("F", lambda g: _integers(plans.estimate_many(g, EIGHT, F_DELTA, K))),
        "estimate_sweep": _on("R", lambda g: _integers(plans.sweep(g, "M4-0", (R_DELTA, 2 * R_DELTA), K))),
        "partition_sampler": _on("R", lambda g: _rounded(baselines.estimate_partition(g, "M4-0", R_DELTA))),
        "edge_sampler": _on("R", lambda g: _rounded(baselines.estimate_edges(g, "M4-0", R_DELTA))),
        "anchor_stats": _anchors,
        "hit_rates": _on("R", lambda g: measures.hit_rates(g, "M4-0", R_DELTA, K).withColumn("w_total", F.col("w_total").cast("bigint"))),
        "hit_rates_folded": _on("F", lambda g: measures.hit_rates(g, "M4-0", F_DELTA, K).withColumn("w_total", F.col("w_total").cast("bigint"))),
        "convergence_in_k": _on("F", lambda g: plans.convergence(g, "M4-0", F_DELTA, GROWING, SEEDS).select("motif", "k", "seed", F.col("cnt").cast("bigint").alias("cnt"))),
        "heuristic_samples": _on("F", _pilots),
        "required_samples": _on("F", _bounds),
        "relative_error_5_seeds": _on("F", _errors),
        "count_table": lambda s, d: measures.count_table({v: (view(s, d, v), delta) for v, _, delta in TABLE}, TABLE[0][1]),
        "count_ratios": _on("F", _ratios),
        "edges_by_label_filter": lambda s, d: graph.reply_graph(s, d).where(F.col("label").isin(*LABELS)).edges,
        "edges_semi_active": _on("R", lambda g: around.active_centers(weights.weights(g, R_DELTA, THROUGH))),
        "edges_anti_isolated": _on("R", around.sources_never_targets),
        "asof_previous_edge": _on("R", around.previous_edge),
        "interval_join_edges": _on("R", _windows_of_days),
        "time_tumbling": _on("R", lambda g: around.tumbling(g, DAY, "label").withColumnRenamed("bucket", "day")),
        "time_sliding": _on("R", lambda g: around.sliding(g, HOUR, 6).withColumnRenamed("bucket", "hour")),
        "time_session": _on("R", lambda g: around.sessions(g, 6 * HOUR)),
        "cube_labels": _on("R", lambda g: g.edges.select("label", F.expr(f"t div {7 * DAY}").alias("week")).cube("label", "week").agg(F.count(F.lit(1)).alias("n"))),
        "rollup_calendar": _on("N", _calendar),
        "grouping_sets_region": _regions,
        "topk_hubs": _on("R", lambda g: around.top_hubs(g, 10)),
        "vertices_union_except_intersect": _on("R", around.vertex_sets),
        "burst_gaps": _on("R", around.gaps),
        "pair_arrays": _on("F", lambda g: around.pair_index(g).select("src", "dst", F.size("ts").cast("bigint").alias("n"), F.array_min("ts").alias("t_first"), F.array_max("ts").alias("t_last"), F.aggregate("ts", F.lit(0).cast("bigint"), lambda a, t: a + F.floor(t / 1_000_000)).alias("t_sum"))),
        "props_json": _topics,
        "degree_deciles": _on("R", around.degree_deciles),
        "induced_subgraph": _on("R", lambda g: g.induced(g.vertices().where("v % 2 = 0")).edges.select("eid", "src", "dst", "t")),
        "time_slice": lambda s, d: graph.nation_graph(s, d).between(9500, 9600).edges,
        "stream_tumbling": _streamed,
    }
    for tag, v, delta, n in WINDOWS:
        for variant in "AE":
            out[f"windows_{variant.lower()}{tag}"] = _on(v, lambda g, variant=variant, delta=delta, n=n: _rounded(baselines.estimate_windows(g, "M4-0", delta, n, variant=variant)))
    for name, (v, names, delta) in WORKLOADS.items():
        out[name] = _on(v, partial(_counts, names=names, delta=delta))
    for name, v, delta in CENSUS:
        out[f"census_{name.lower().replace('-', '_')}"] = _on(v, partial(plans.census, which=name, delta=delta))
    for name, v, delta in EXACT:
        key = name.lower().replace("-", "_")
        out[f"backtrack_{key}"] = _on(v, partial(exact.exact_backtrack, which=name, delta=delta))
        out[f"frontier_{key}"] = _on(v, partial(exact.exact_frontier, which=name, delta=delta))
    for name in (*EIGHT, "TRI", "LATE", "SPLIT", "PAW"):
        out[f"estimate_{name.lower().replace('-', '_')}"] = _on("F", lambda g, name=name: _integers(plans.estimate(g, name, F_DELTA, K)))
    return out
