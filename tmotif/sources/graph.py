"""Temporal graphs as edge tables, and edge views over the given tables."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tmotif.operators.prefix import with_previous
from tmotif.sources.io import staged

MICROSECONDS = {"W": 604_800_000_000, "D": 86_400_000_000, "H": 3_600_000_000}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load_tables(spark: SparkSession, sf_dir: str, names=("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events")) -> dict[str, DataFrame]:
    return {n: table(spark, sf_dir, n) for n in names}


@dataclass(frozen=True)
class TemporalGraph:
    """Directed temporal multigraph: a table eid, src, dst, t (all bigint), perhaps label; no loops; (t, eid) is a total order."""

    edges: DataFrame
    unit: str = "us"

    @classmethod
    def from_table(cls, df: DataFrame, src: str, dst: str, t: str, eid: str | None = None, label: str | None = None, unit: str = "us", keep_loops: bool = False) -> TemporalGraph:
        """Any table; timestamps become microseconds, dates days. Rows with a null end or time are not edges."""
        kinds = dict(df.dtypes)
        time = F.col(t)
        if kinds[t].startswith("timestamp"):
            time = F.unix_micros(time.cast("timestamp"))
        elif kinds[t] == "date":
            time = F.unix_date(time)
        number = F.col(eid) if eid else F.monotonically_increasing_id()
        out = df.select(number.cast("bigint").alias("eid"), F.col(src).cast("bigint").alias("src"), F.col(dst).cast("bigint").alias("dst"), time.cast("bigint").alias("t"), *([F.col(label).alias("label")] if label else []))
        out = out.where("src is not null and dst is not null and t is not null")
        out = out if keep_loops else out.where("src <> dst")
        return cls(out if eid else staged(out, "edges"), unit)  # numbers given here must not change when read again

    @classmethod
    def from_rows(cls, spark: SparkSession, rows: list[tuple[int, int, int]]) -> TemporalGraph:
        """Literal (src, dst, t) rows, numbered in order."""
        df = spark.createDataFrame([(i, *r) for i, r in enumerate(rows)], "eid bigint, src bigint, dst bigint, t bigint")
        return cls(df)

    def with_edges(self, edges: DataFrame) -> TemporalGraph:
        return TemporalGraph(edges, self.unit)

    def without_loops(self) -> TemporalGraph:
        return self.with_edges(self.edges.where("src <> dst"))

    def between(self, a: int, b: int) -> TemporalGraph:
        """Edges with a <= t <= b."""
        return self.with_edges(self.edges.where(F.col("t").between(a, b)))

    def where(self, condition: str | Column) -> TemporalGraph:
        return self.with_edges(self.edges.where(condition))

    def induced(self, vertices: DataFrame) -> TemporalGraph:
        """Edges with both ends among the vertices (column v)."""
        kept = self.edges.join(vertices.select(F.col("v").alias("src")), "src", "left_semi").join(vertices.select(F.col("v").alias("dst")), "dst", "left_semi")
        return self.with_edges(kept.select(*self.edges.columns))

    def staged(self) -> TemporalGraph:
        """The same edges, written once to the shared folder for the many passes of an estimate."""
        return self.with_edges(staged(self.edges, "edges"))

    def simple(self) -> TemporalGraph:
        """One edge a pair, the first one."""
        first = self.edges.groupBy("src", "dst").agg(F.min(F.struct("t", "eid")).alias("x"))
        return self.with_edges(first.select(F.col("x.eid").alias("eid"), "src", "dst", F.col("x.t").alias("t")))

    def vertices(self) -> DataFrame:
        return self.edges.select(F.explode(F.array("src", "dst")).alias("v")).distinct()

    def static_edges(self) -> DataFrame:
        return self.edges.select("src", "dst").distinct()

    def profile(self) -> DataFrame:
        """One row: vertices, temporal_edges, static_edges, t_min, t_max, span."""
        whole = self.edges.agg(F.count(F.lit(1)).alias("temporal_edges"), F.min("t").alias("t_min"), F.max("t").alias("t_max"))
        n, s = self.vertices().agg(F.count(F.lit(1)).alias("vertices")), self.static_edges().agg(F.count(F.lit(1)).alias("static_edges"))
        return n.crossJoin(whole).crossJoin(s).select("vertices", "temporal_edges", "static_edges", "t_min", "t_max", (F.col("t_max") - F.col("t_min")).alias("span"))  # three single rows

    def approximate_vertices(self) -> DataFrame:
        return self.edges.select(F.explode(F.array("src", "dst")).alias("v")).agg(F.approx_count_distinct("v").alias("vertices"))

    def both_roles(self) -> DataFrame:
        """Each edge under each of its ends: dir '+' under its source, '-' under its target."""
        return self.edges.select("eid", "t", F.inline(F.array(F.struct(F.lit("+").alias("dir"), F.col("src").alias("vertex"), F.col("dst").alias("other")), F.struct(F.lit("-").alias("dir"), F.col("dst").alias("vertex"), F.col("src").alias("other")))))


def _micros(name: str) -> Column:
    return F.unix_micros(F.col(name).cast("timestamp"))


def _day(name: str) -> Column:
    return F.unix_date(F.to_date(F.col(name))).cast("bigint")


def previous_in_topic(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events with the user of the previous event of the same topic (an as-of step by lag)."""
    events = table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", "props")
    topic = F.get_json_object("props", "$.k").cast("int")
    rows = events.withColumn("topic", topic).withColumn("bucket", F.to_date("ts"))
    return with_previous(rows, ["topic"], ["ts", "event_id"], {"user_id": "previous"}).where("previous is not null")


def reply_graph(spark: SparkSession, sf_dir: str, fold: int | None = None, keep_loops: bool = False) -> TemporalGraph:
    """R: each event answers the previous one of its topic. With fold, user ids modulo fold."""
    rows = previous_in_topic(spark, sf_dir)
    user, previous = (F.col(c).cast("bigint") % fold if fold else F.col(c).cast("bigint") for c in ("user_id", "previous"))
    edges = rows.select(F.col("event_id").cast("bigint").alias("eid"), user.alias("src"), previous.alias("dst"), _micros("ts").alias("t"), F.col("event_type").alias("label"))
    return TemporalGraph(edges if keep_loops else edges.where("src <> dst"))


def numbered_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate")
    by = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_shipdate")
    return lines.withColumn("line_id", F.col("l_orderkey") * 1000 + F.row_number().over(by))


def nation_graph(spark: SparkSession, sf_dir: str) -> TemporalGraph:
    """N: customer nation to supplier nation at the day of shipping."""
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    customers = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("o_custkey"), F.col("c_nationkey").cast("bigint").alias("src"))
    suppliers = table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), F.col("s_nationkey").cast("bigint").alias("dst"))
    rows = numbered_lines(spark, sf_dir).join(orders, "l_orderkey").join(customers, "o_custkey").join(suppliers, "l_suppkey")
    return TemporalGraph(rows.select(F.col("line_id").cast("bigint").alias("eid"), "src", "dst", _day("l_shipdate").alias("t")).where("src <> dst"), "day")


def trade_graph(spark: SparkSession, sf_dir: str, numbered: bool = True) -> TemporalGraph:
    """T: customer to supplier at the day of the order, supplier to customer at the day of shipping; bipartite by parity. Not numbered: src, dst and t only, so that no line is sorted."""
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey", "o_orderdate")
    lines = numbered_lines(spark, sf_dir) if numbered else table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", "l_shipdate")
    rows = lines.join(orders, "l_orderkey")
    buyer, seller = (F.col("o_custkey") * 2).cast("bigint"), (F.col("l_suppkey") * 2 + 1).cast("bigint")
    if not numbered:
        halves = F.array(F.struct(buyer.alias("src"), seller.alias("dst"), _day("o_orderdate").alias("t")), F.struct(seller.alias("src"), buyer.alias("dst"), _day("l_shipdate").alias("t")))
        return TemporalGraph(rows.select(F.inline(halves)), "day")
    eid = (F.col("line_id") * 2).cast("bigint")
    halves = F.array(
        F.struct(eid.alias("eid"), buyer.alias("src"), seller.alias("dst"), _day("o_orderdate").alias("t"), F.lit("order").alias("label")),
        F.struct((eid + 1).alias("eid"), seller.alias("src"), buyer.alias("dst"), _day("l_shipdate").alias("t"), F.lit("ship").alias("label")),
    )
    return TemporalGraph(rows.select(F.inline(halves)), "day")
