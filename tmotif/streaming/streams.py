"""Edges as streams: watermarked ingest, windows, wedges as they close, estimates per complete bucket."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from tmotif.functions.motif import PathClass
from tmotif.plans.estimate import estimate
from tmotif.sources.graph import TemporalGraph

STREAM_SCHEMA = "eid bigint, src bigint, dst bigint, ts timestamp, label string"


def stream_edges(spark: SparkSession, path: str, delay: str, schema: str = STREAM_SCHEMA, fmt: str = "parquet", files: int | None = None) -> DataFrame:
    reader = spark.readStream.schema(schema).format(fmt)
    if files:
        reader = reader.option("maxFilesPerTrigger", files)
    return reader.load(path).withWatermark("ts", delay)


def dedup_edges(stream: DataFrame) -> DataFrame:
    return stream.dropDuplicatesWithinWatermark(["eid"])


def stream_tumbling(stream: DataFrame, width: str, *by: str) -> DataFrame:
    return stream.groupBy(F.window("ts", width), *by).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), *by, "n")


def stream_sliding(stream: DataFrame, width: str, step: str, *by: str) -> DataFrame:
    return stream.groupBy(F.window("ts", width, step), *by).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), *by, "n")


def stream_sessions(stream: DataFrame, gap: str) -> DataFrame:
    return stream.groupBy(F.session_window("ts", gap), "src").agg(F.count(F.lit(1)).alias("n")).select("src", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "n")


def stream_wedges(stream: DataFrame, delta: str) -> DataFrame:
    """Out-edges of a base edge's target within delta after it, from a stream-stream join with both watermarks."""
    base = stream.select(F.col("eid").alias("eid1"), F.col("src").alias("v0"), F.col("dst").alias("v1"), F.col("ts").alias("ts1"))
    other = stream.select(F.col("eid").alias("eid2"), F.col("src").alias("v1_"), F.col("dst").alias("v2"), F.col("ts").alias("ts2"))
    on = (F.col("v1") == F.col("v1_")) & (F.col("ts2") > F.col("ts1")) & (F.col("ts2") <= F.col("ts1") + F.expr(f"interval {delta}"))
    return base.join(other, on).select("eid1", "eid2", "v0", "v1", "v2", "ts1", "ts2")


def stream_degrees(stream: DataFrame, delta_seconds: int) -> DataFrame:
    """eid, vertex, n: in-edges of an edge's source within delta before it, with one list of recent edges per vertex as state.

    Rows of a vertex are taken in time order within a batch; times older than twice delta before the newest are dropped from the state.
    """
    import pandas as pd

    def update(key, frames, state):
        recent = list(state.get[0]) if state.exists else []
        rows = pd.concat(list(frames)).sort_values(["us", "role"])
        out = []
        width = delta_seconds * 1_000_000
        for us, role, eid in zip(rows["us"], rows["role"], rows["eid"], strict=True):
            if role:  # data after probes at equal times: strict
                recent.append(int(us))
            else:
                out.append((int(eid), key[0], sum(us - width <= x < us for x in recent)))
        newest = int(rows["us"].max())
        recent = [x for x in recent if x >= newest - 2 * width]
        state.update((recent,))
        yield pd.DataFrame(out, columns=["eid", "vertex", "n"])

    us = F.unix_micros("ts")
    roles = F.array(F.struct(F.col("dst").alias("vertex"), F.lit(1).alias("role")), F.struct(F.col("src").alias("vertex"), F.lit(0).alias("role")))
    rows = stream.select("eid", us.alias("us"), F.inline(roles))
    return rows.groupBy("vertex").applyInPandasWithState(update, "eid bigint, vertex bigint, n bigint", "recent array<bigint>", "append", "NoTimeout")


def stream_weights(stream: DataFrame, delta_seconds: int, cls: PathClass = PathClass("-", "+", "<", ">")) -> DataFrame:
    """eid, slot ('n1' at the source, 'n3' at the target), n: both windowed degrees of each edge, once the watermark has passed their windows.

    A vertex's state is the times of its edges and the edges that wait; a timer at the end of the earliest
    window wakes a vertex that gets no more edges, and drops what no later edge can ask for. Edges behind the
    watermark are not counted. The weight of an edge is the product of its two rows.
    """
    import pandas as pd

    width = delta_seconds * 1_000_000
    ends = {"n1": (cls.a1, cls.b1), "n3": (cls.a3, cls.b3)}
    over = {k: (0 if side == "<" else width) for k, (_, side) in ends.items()}

    def update(key, frames, state):
        plus, minus, eids, slots, times = (list(x) for x in state.get) if state.exists else ([], [], [], [], [])
        if not state.hasTimedOut:
            rows = pd.concat(list(frames))
            for us, kind, eid in zip(rows["us"], rows["kind"], rows["eid"], strict=True):
                if kind in "+-":
                    (plus if kind == "+" else minus).append(int(us))
                else:
                    eids.append(int(eid))
                    slots.append(kind)
                    times.append(int(us))
        mark = max(0, state.getCurrentWatermarkMs()) * 1000
        out, rest = [], []
        for eid, slot, t in zip(eids, slots, times, strict=True):
            if t + over[slot] >= mark:
                rest.append((eid, slot, t))
                continue
            sign, side = ends[slot]
            near = plus if sign == "+" else minus
            out.append((eid, slot, sum(t - width <= s < t if side == "<" else t < s <= t + width for s in near)))
        oldest = min([mark, *(t for _, _, t in rest)]) - width
        plus, minus = [s for s in plus if s >= oldest], [s for s in minus if s >= oldest]
        if rest or plus or minus:
            state.update((plus, minus, [r[0] for r in rest], [r[1] for r in rest], [r[2] for r in rest]))
            wake = min((t + over[slot] for _, slot, t in rest), default=max([*plus, *minus], default=0) + width)
            state.setTimeoutTimestamp(max(wake, mark) // 1000 + 1)
        elif state.exists:
            state.remove()
        yield pd.DataFrame(out, columns=["eid", "slot", "n"])

    kinds = [F.struct(F.col("src").alias("vertex"), F.lit("n1").alias("kind")), F.struct(F.col("dst").alias("vertex"), F.lit("n3").alias("kind"))]
    kinds += [F.struct(F.col("src" if sign == "+" else "dst").alias("vertex"), F.lit(sign).alias("kind")) for sign in sorted({cls.a1, cls.a3})]
    rows = stream.select("eid", "ts", F.unix_micros("ts").alias("us"), F.inline(F.array(*kinds)))
    kept = "plus array<bigint>, minus array<bigint>, eids array<bigint>, slots array<string>, times array<bigint>"
    return rows.groupBy("vertex").applyInPandasWithState(update, "eid bigint, slot string, n bigint", kept, "append", "EventTimeTimeout")


def stream_estimate(stream: DataFrame, which: str, delta: int, k: int, keep: Callable[[DataFrame], None]) -> StreamingQuery:
    """An estimate of each micro-batch's own edges (batches are whole time buckets); keep gets one row a batch."""

    def batch(df: DataFrame, number: int) -> None:
        edges = df.select("eid", "src", "dst", F.unix_micros("ts").alias("t"))
        keep(estimate(TemporalGraph(edges), which, delta, k).withColumn("batch", F.lit(number)))

    return stream.writeStream.foreachBatch(batch).trigger(availableNow=True).start()


def drained(out: DataFrame, folder: str, mode: str = "append") -> DataFrame:
    """Runs a stream over all that is there, into parquet, and reads the result."""
    name = uuid.uuid4().hex
    query = out.writeStream.format("parquet").outputMode(mode).option("path", f"{folder}/out-{name}").option("checkpointLocation", f"{folder}/log-{name}").trigger(availableNow=True).start()
    query.awaitTermination()
    return out.sparkSession.read.schema(out.schema).parquet(f"{folder}/out-{name}")


def late_rows(query: StreamingQuery) -> int:
    """Rows that came behind the watermark and were dropped, from the progress reports."""
    return sum(int(op["numRowsDroppedByWatermark"]) for p in query.recentProgress for op in p["stateOperators"])
