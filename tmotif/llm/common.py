"""Shared plumbing of the training-data operators: staging, text tables, components.

Conventions shared by all operators of this subpackage: input columns are
chosen by name and copied to internal names, so extra columns never clash; a
null text counts as empty; null ids are kept as rows and sort after all others;
an empty table gives an empty result with the same columns.
"""

from __future__ import annotations

import ctypes
import os
import tempfile
import uuid
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: White space of the contracts, as a Java/RE2 class and as regular expression.
SPACE_CLASS = r"[\x20\x09-\x0D]+"
WORD_CLASS = r"[^\x20\x09-\x0D]+"
#: Stands for "no id" in packed runs; no real id may have it.
NO_ID = np.iinfo(np.int64).max


def workspace(spark: SparkSession) -> str:
    """The folder that all executors share. Only a local master may fall back to a temporary one."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        folder = spark.conf.get("tmotif.workspace", None)
        if not folder:
            folder = tempfile.mkdtemp(prefix="tmotif-")
            spark.conf.set("tmotif.workspace", folder)
    return folder


def staged(df: DataFrame, label: str) -> DataFrame:
    """Write once to the shared folder and read back: cuts the lineage, survives lost executors."""
    path = f"{workspace(df.sparkSession)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def workers_see_package(spark: SparkSession) -> None:
    """Let Python workers on this machine import the package; a cluster ships it with --py-files."""
    root = str(Path(__file__).resolve().parents[2])
    have = spark.sparkContext.environment.get("PYTHONPATH", "")
    if root not in have.split(os.pathsep):
        spark.sparkContext.environment["PYTHONPATH"] = os.pathsep.join(x for x in (root, have) if x)


def text_table(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", *more: str) -> DataFrame:
    """Columns doc_id (long) and text (null: empty), then those in more, and no others."""
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"), *more)


#: Rows of two numbers that may be broadcast (8 MB, and some three times that as a table); more are joined by a shuffle.
BROADCAST_ROWS = 500_000


def shuffled(rows: DataFrame) -> DataFrame:
    """Rows that are not broadcast, nor what they are joined to.

    The planner takes a staged table for as small as its files, and rows made by explode for as few as those they
    come from, so that it would send to the driver what grows with the input.
    """
    return rows.hint("merge")


def marked(rows: DataFrame, numbers: DataFrame) -> DataFrame:
    """rows with marked, whether their row number is in the column row of numbers. Sixty-four row numbers, which follow each other in a file, are one word of bits to be broadcast."""
    at = F.call_function("shiftleft", F.lit(1).cast("long"), F.expr("cast(row & 63L as int)"))
    words = staged(numbers.groupBy(F.shiftright("row", 6).alias("word_")).agg(F.bit_or(at).alias("bits_")), "marks")
    words = F.broadcast(words) if words.count() <= BROADCAST_ROWS else shuffled(words)
    joined = rows.join(words, F.shiftright("row", 6) == F.col("word_"), "left")
    return joined.withColumn("marked", F.coalesce(F.col("bits_").bitwiseAND(at) != 0, F.lit(False))).drop("word_", "bits_")


def numbered(docs: DataFrame, stable: bool) -> DataFrame:
    """docs as c0, c1, .. and row, a number of each row that stays the same whenever the result is read.

    stable says that docs is a plain scan of files that don't change, whose rows
    Spark numbers alike each time; anything else is staged first.
    """
    out = docs.select(*[F.col(f"`{c}`").alias(f"c{k}") for k, c in enumerate(docs.columns)], F.monotonically_increasing_id().alias("row"))
    return out if stable else staged(out, "rows")


def without(rows: DataFrame, gone: DataFrame, names: list[str]) -> DataFrame:
    """numbered() rows except those numbers, under their own column names."""
    return marked(rows, gone).where("not marked").select(*[F.col(f"c{k}").alias(c) for k, c in enumerate(names)])


#: Bytes of a batch that a function is given at once, if it has several rows.
SLICE_BYTES = 2 << 20


def _in_slices(function):
    """The function over batches of a bounded size, so that what it makes of one stays small."""

    def make(batches):
        def slices():
            for batch in batches:
                step = max(1, batch.num_rows * SLICE_BYTES // max(1, batch.nbytes))
                for k in range(0, batch.num_rows, step):
                    yield batch.slice(k, step)

        yield from function(slices())
        give_back()

    return make


def give_back() -> None:
    """What a worker has freed goes back to the machine, since workers outlive their tasks."""
    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
        trim(0)


def executors_give_back(spark: SparkSession) -> int:
    """Each executor collects its garbage, so that heap that an earlier stage has grown to, and buffers outside the heap that only garbage holds, go back to the machine. Returns the tasks that did so, one a core.

    The driver does so after them, since it keeps broadcasts, results and plans of the stages before until it does.
    """
    n = max(1, spark.sparkContext.defaultParallelism)
    done = len(spark.range(0, n, 1, n).select(F.call_function("java_method", F.lit("java.lang.System"), F.lit("gc"))).collect())
    spark.sparkContext._jvm.System.gc()
    return done


#: Rows of an Arrow batch on its way to a worker; a session that has another value than Spark's own keeps it.
BATCH_ROWS, BATCH_KEY = 1000, "spark.sql.execution.arrow.maxRecordsPerBatch"


def in_arrow(df: DataFrame, function, schema: str) -> DataFrame:
    workers_see_package(df.sparkSession)
    if df.sparkSession.conf.get(BATCH_KEY) == "10000":  # whole texts and hash sets: ten thousand rows are some 50 MB on either side
        df.sparkSession.conf.set(BATCH_KEY, BATCH_ROWS)
    return df.mapInArrow(_in_slices(function), schema)


def _stars(batches):
    """Union-find over the links of one task: each node once, with the smallest node it reaches there."""
    parent: dict[int, int] = {}

    def root(x: int) -> int:
        parent.setdefault(x, x)
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for batch in batches:
        for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            a, b = root(a), root(b)
            if a != b:
                parent[max(a, b)] = min(a, b)
    pairs = [(x, r) for x in list(parent) if (r := root(x)) != x]
    for k in range(0, len(pairs), 100_000):
        part = pairs[k : k + 100_000]
        yield pa.RecordBatch.from_arrays([pa.array([p[0] for p in part], pa.int64()), pa.array([p[1] for p in part], pa.int64())], ["hi", "lo"])


def components(links: DataFrame) -> DataFrame:
    """Connected components of links (two long columns): rows (node, root), root the smallest node.

    Each task first shrinks its own links to stars; then alternating large-star
    and small-star rounds, each written to the shared folder, until nothing
    moves. Every link is used; nodes without links are not listed.
    """
    a, b = links.columns[:2]
    edges = in_arrow(links.select(F.col(a).cast("long").alias("a"), F.col(b).cast("long").alias("b")).where("a <> b"), _stars, "hi long, lo long")
    edges, before = staged(edges.distinct(), "links"), None
    while True:
        mark = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("hi", "lo") % 1_000_000_007)).first()
        if mark == before or not mark[0]:
            return edges.select(F.col("hi").alias("node"), F.col("lo").alias("root"))
        before = mark
        both = edges.union(edges.select("lo", "hi")).toDF("u", "v")
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = shuffled(both.where("v > u")).join(least, "u").select(F.col("v").alias("hi"), F.col("m").alias("lo")).distinct()
        least = large.groupBy("hi").agg(F.min("lo").alias("m"))
        small = shuffled(large).join(least, "hi").select(F.explode(F.array(F.struct(F.col("hi").alias("hi"), F.col("m").alias("lo")), F.struct(F.col("lo").alias("hi"), F.col("m").alias("lo")))).alias("e")).select("e.hi", "e.lo").where("hi <> lo").distinct()
        edges = staged(in_arrow(small, _stars, "hi long, lo long").distinct(), "links")
