"""Plans: no product joins, no Python on the default path; streams equal batches; SQL functions."""

import random
import time

import pytest
from pyspark.sql import Window
from pyspark.sql import functions as F

from tmotif.functions import sqlapi
from tmotif.functions.motif import PathClass
from tmotif.operators import around, sampling, weights
from tmotif.operators.prefix import running_in_keys, running_total, with_previous
from tmotif.plans.estimate import census, estimate
from tmotif.sources import io
from tmotif.sources.graph import TemporalGraph, reply_graph
from tmotif.sources.io import read_edges
from tmotif.streaming import streams

SF = "/root/testdata/sf0.001"
DAY = 86_400_000_000


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_default_plans(spark):
    tg = reply_graph(spark, SF)
    w = plan(weights.weights(tg, DAY, PathClass("-", "+", "<", ">")))
    c = plan(census(tg, "M4-5", DAY))
    for text in (w, c):
        assert "Cartesian" not in text and "NestedLoop" not in text and "Python" not in text and "Arrow" not in text


def test_pushdown(spark):
    text = plan(reply_graph(spark, SF).edges)
    assert "ReadSchema: struct<event_id:bigint,ts:timestamp_ntz,user_id:bigint,event_type:string,props:string>" in text


@pytest.fixture
def edge_folder(spark, tmp_path):
    rows = [(i, i % 5, (i * 3 + 1) % 5, f"2024-01-0{1 + i // 10} 0{i % 10}:00:00", "x") for i in range(30)]
    df = spark.createDataFrame(rows, "eid bigint, src bigint, dst bigint, ts string, label string").selectExpr("eid", "src", "dst", "cast(ts as timestamp) ts", "label")
    df.coalesce(1).write.parquet(str(tmp_path / "edges"))
    return str(tmp_path / "edges"), df, tmp_path


def test_stream_wedges_equal_batch(spark, edge_folder):
    folder, df, tmp = edge_folder
    got = streams.drained(streams.stream_wedges(streams.stream_edges(spark, folder, "10 days"), "3 hours"), str(tmp / "o"))
    want = df.alias("a").join(df.alias("b"), on=None, how="cross").where("a.dst = b.src and b.ts > a.ts and b.ts <= a.ts + interval 3 hours")
    assert got.count() == want.count() > 0


def test_stream_degrees_equal_batch(spark, edge_folder):
    folder, df, tmp = edge_folder
    stream = streams.dedup_edges(streams.stream_edges(spark, folder, "1 hour"))
    got = {r["eid"]: r["n"] for r in streams.drained(streams.stream_degrees(stream, 3 * 3600), str(tmp / "o")).collect()}
    rows = df.collect()
    assert got == {e["eid"]: sum(f["dst"] == e["src"] and 0 < (e["ts"] - f["ts"]).total_seconds() <= 3 * 3600 for f in rows) for e in rows}


def test_text_edges_and_sql(spark, tmp_path):
    (tmp_path / "e.txt").write_text("# comment\n1 2 10\n2\t3 20\n3 1 30\n3 3 5\n")
    tg = read_edges(spark, str(tmp_path / "e.txt"), "text")
    assert tg.edges.count() == 3 and census(tg, "TRI", 100).first()["count"] == 1
    sqlapi.register(spark)
    assert spark.sql("SELECT * FROM motif_edges('TRI')").count() == 3
    assert spark.sql("SELECT rel_error(10D, 9D) e").first()["e"] == pytest.approx(0.1)
    assert spark.sql("SELECT chain_count(array(1, 2, 3), array(0, 1, 1), 2) x").first()["x"] == 2


def test_adapter_drops_nulls(spark):
    df = spark.createDataFrame([(1, 2, 3, "a"), (None, 2, 3, "b"), (4, 4, 1, "c")], "a int, b int, c int, src string")
    assert TemporalGraph.from_table(df, "a", "b", "c").edges.drop("eid").collect() == [(1, 2, 3)]


def test_estimate_plan(spark):
    """No nested loop, no product, no Python in an estimate on either kind of sampler; its size does not grow with the buckets."""
    tg = reply_graph(spark, SF).staged()
    for sampler in ("centered", "static", "constrained"):
        text = plan(estimate(tg, "M4-0", DAY, 500, sampler=sampler))
        assert "Cartesian" not in text and "NestedLoop" not in text and "Python" not in text and "Arrow" not in text
    cls = PathClass("-", "+", "<", ">")
    sizes = [len(plan(weights.with_offsets(weights.weights(tg, DAY, cls), buckets=n))) for n in (3, 60)]
    assert abs(sizes[0] - sizes[1]) < 200


def test_many_draws_are_not_broadcast(spark, monkeypatch):
    monkeypatch.setattr(sampling, "BROADCAST_DRAWS", 100)
    tg = reply_graph(spark, SF).staged()
    few = estimate(tg, "M4-0", 2 * DAY, 20_000).first()
    assert round(few["estimate"], 4) == 476.3544


def test_hot_day_is_cut(spark):
    """All edges at one time: the running total still has several buckets, none with most rows."""
    rows = spark.range(1000).selectExpr("id eid", "5L t", "1L w")
    got = running_total(rows, F.col("w"), ["t", "eid"], "first", buckets=8)
    assert got.groupBy("part").count().agg(F.max("count")).first()[0] < 500
    assert [r["first"] for r in got.orderBy("eid").select("first").collect()] == list(range(1000))


def test_bucketed_windows(spark):
    """Previous rows and running sums across empty buckets, ties and null keys."""
    rnd = random.Random(3)
    data = [(i, rnd.choice([1, 2, None]), rnd.randrange(60), rnd.randrange(5)) for i in range(200)]
    df = spark.createDataFrame(data, "eid int, k int, t int, v int").withColumn("bucket", F.expr("t div 7"))
    order = Window.partitionBy("k").orderBy("t", "eid")
    for back, other in ((False, F.lag), (True, F.lead)):
        want = {r["eid"]: r["p"] for r in df.withColumn("p", other("t").over(order)).collect()}
        assert {r["eid"]: r["p"] for r in with_previous(df, ["k"], ["t", "eid"], {"t": "p"}, back=back).collect()} == want
    want = {r["eid"]: r["s"] for r in df.where("k is not null").withColumn("s", F.sum("v").over(order)).collect()}
    assert {r["eid"]: r["s"] for r in running_in_keys(df.where("k is not null"), ["k"], ["t", "eid"], "v", "s").collect()} == want


def test_files_and_tables(spark, tmp_path):
    rows = [(1, 2, 10), (2, 3, 20), (3, 1, 30)]
    df = spark.createDataFrame(rows, "src bigint, dst bigint, t bigint")
    for fmt in ("parquet", "orc", "json", "csv"):
        writer = df.write.option("header", True) if fmt == "csv" else df.write
        writer.format(fmt).save(str(tmp_path / fmt))
        tg = read_edges(spark, str(tmp_path / fmt), fmt)
        assert sorted(tg.edges.drop("eid").collect()) == rows and census(tg, "TRI", 100).first()["count"] == 1
    io.write_pair_index(tg, "pairs_test", 2)
    io.write_incidence(tg, "lists_test", 100, 2)
    assert spark.table("pairs_test").count() == 3 and spark.table("lists_test").count() == 6
    assert "Exchange" not in plan(spark.table("pairs_test").groupBy("src", "dst").count())
    io.write_results(census(tg, "TRI", 100), str(tmp_path / "out"), "motif")
    io.write_results(census(tg, "TRI", 100), str(tmp_path / "out"), "motif")
    assert spark.read.parquet(str(tmp_path / "out")).where("motif = 'TRI'").count() == 2
    for name in ("pairs_test", "lists_test"):
        spark.sql(f"DROP TABLE {name}")


def test_sql_functions(spark):
    sqlapi.register(spark)
    assert [r["anchor"] for r in spark.sql("SELECT * FROM motif_anchors('M4-0')").collect()][0] == "0,1,2"
    assert spark.sql("SELECT * FROM motif_sample_bound(2D, 1, 100D, 10D, 0.1D, 0.05D)").first()["k"] == 22134
    assert spark.sql("SELECT rel_error(0D, 1D) e").first()["e"] is None
    rows = "VALUES (1, 3, 1), (1, 1, 0), (1, 2, 0), (1, 2, 1), (1, 4, 1), (2, 1, 1), (2, 2, 0) AS r(k, t, pos)"
    assert {tuple(r) for r in spark.sql(f"SELECT k, chain_total(t, pos, 2) x FROM {rows} GROUP BY k").collect()} == {(1, 5), (2, 0)}
    assert sqlapi.catalog_table(spark).where("motif = 'M4-1'").count() == 9


def test_pairs_within(spark):
    rnd = random.Random(4)
    rows = [(i, rnd.randrange(-50, 50)) for i in range(40)]
    got = {tuple(r) for r in around.pairs_within(spark.createDataFrame(rows, "id int, t int"), 6).collect()}
    assert got == {(a, b) for a, s in rows for b, t in rows if a < b and abs(s - t) <= 6}


def test_stream_windows_equal_batch(spark, edge_folder):
    folder, df, tmp = edge_folder
    read = lambda: streams.stream_edges(spark, folder, "1 hour")
    end = F.unix_timestamp("start")
    got = streams.drained(streams.stream_sliding(read(), "4 hours", "2 hours"), str(tmp / "a")).select(end, "n").collect()
    want = {(r[0], r[1]) for r in df.groupBy(F.window("ts", "4 hours", "2 hours")).count().select(F.unix_timestamp("window.start"), "count").collect()}
    assert got and {tuple(r) for r in got} <= want
    got = streams.drained(streams.stream_sessions(read(), "90 minutes"), str(tmp / "b")).collect()
    want = {(r["src"], r["start"], r["n"]) for r in df.groupBy(F.session_window("ts", "90 minutes"), "src").count().selectExpr("src", "session_window.start start", "count n").collect()}
    assert got and {(r["src"], r["start"], r["n"]) for r in got} <= want


def test_stream_estimates(spark, edge_folder):
    folder, df, _ = edge_folder
    kept = []
    streams.stream_estimate(streams.stream_edges(spark, folder, "1 hour"), "TRI", 10 * 3_600_000_000, 500, lambda row: kept.append(row.first())).awaitTermination()
    exact = census(TemporalGraph(df.selectExpr("eid", "src", "dst", "unix_micros(ts) t")), "TRI", 10 * 3_600_000_000).first()["count"]
    assert len(kept) == 1 and abs(kept[0]["estimate"] - exact) <= 5 * kept[0]["stderr"] + 1


def test_late_rows(spark, tmp_path):
    """Rows far behind the watermark are dropped and counted."""
    days = [["2024-01-05", "2024-01-06"], ["2024-01-09"], ["2024-01-01", "2024-01-02", "2024-01-09"]]
    for k, some in enumerate(days):
        rows = [(10 * k + i, 1, 2, f"{d} 00:00:00", "x") for i, d in enumerate(some)]
        spark.createDataFrame(rows, "eid bigint, src bigint, dst bigint, ts string, label string").selectExpr("eid", "src", "dst", "cast(ts as timestamp) ts", "label").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        time.sleep(1.1)
    stream = streams.stream_edges(spark, str(tmp_path / "in"), "1 day", files=1)
    out = streams.stream_tumbling(stream, "1 day")
    query = out.writeStream.format("parquet").outputMode("append").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "log")).trigger(availableNow=True).start()
    query.awaitTermination()
    assert streams.late_rows(query) == 2


def test_stream_weights(spark, tmp_path):
    """Both degrees of every edge, as batches arrive and timers fire; a last edge far ahead drives the watermark."""
    rnd = random.Random(6)
    hour = 3600
    rows = sorted((rnd.randrange(72 * hour), rnd.randrange(4), rnd.randrange(4)) for _ in range(120))
    rows = [(i, a, (b + 1) % 5 if a == b else b, t) for i, (t, a, b) in enumerate(rows)]
    every = [*rows, (900, 7, 8, 400 * hour), (901, 8, 9, 800 * hour)]
    for part in (rows[:50], rows[50:90], rows[90:], every[-2:-1], every[-1:]):
        spark.createDataFrame(part, "eid bigint, src bigint, dst bigint, s bigint").selectExpr("eid", "src", "dst", "timestamp_seconds(s) ts", "'x' label").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        time.sleep(1.1)
    stream = streams.stream_edges(spark, str(tmp_path / "in"), "1 hour", files=1)
    out = streams.drained(streams.stream_weights(stream, 5 * hour), str(tmp_path / "o")).collect()
    got = {(r["eid"], r["slot"]): r["n"] for r in out}
    assert len(got) == len(out)
    graph = TemporalGraph(spark.createDataFrame(rows, "eid bigint, src bigint, dst bigint, t bigint"))
    want = {}
    for r in weights.weights(graph, 5 * hour, PathClass("-", "+", "<", ">")).collect():
        want |= {(r["eid"], "n1"): r["n1"], (r["eid"], "n3"): r["n3"]}
    assert {k: n for k, n in got.items() if k[0] < 900} == want
