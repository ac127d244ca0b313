"""Edge lists in files, bucketed indexes, results."""

from __future__ import annotations

import os
import tempfile
import uuid
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F



def workspace(spark: SparkSession) -> str:
    """The folder that all executors share. Only a local master may fall back to a temporary one."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("tmotif.workspace", None)
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        folder = tempfile.mkdtemp(prefix="tmotif-")
        spark.conf.set("tmotif.workspace", folder)
    return folder


def staged(df: DataFrame, label: str) -> DataFrame:
    """Written once to the shared folder and read back: cuts the lineage, and row numbers made before stay what they are."""
    path = f"{workspace(df.sparkSession)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def workers_see_package(spark: SparkSession) -> None:
    """Let Python workers on this machine import the package; a cluster ships it with --py-files."""
    root = str(Path(__file__).resolve().parents[2])
    have = spark.sparkContext.environment.get("PYTHONPATH", "")
    if root not in have.split(os.pathsep):
        spark.sparkContext.environment["PYTHONPATH"] = os.pathsep.join(x for x in (root, have) if x)


EDGE_SCHEMA = "src bigint, dst bigint, t bigint"


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", unit: str = "s"):
    """fmt: parquet, orc, json, csv (header), or text (white-space separated src dst t; lines that begin with # or % are skipped)."""
    from tmotif.sources.graph import TemporalGraph

    if fmt == "text":
        lines = spark.read.text(path).where(~F.col("value").rlike(r"^\s*[#%]") & F.col("value").rlike(r"\S"))
        cells = F.split(F.trim("value"), r"[\s,]+")
        df = lines.select(*[F.get(cells, F.lit(i)).cast("bigint").alias(c) for i, c in enumerate(("src", "dst", "t"))])
    elif fmt in ("csv", "json"):
        reader = spark.read.schema(EDGE_SCHEMA)
        df = reader.csv(path, header=True) if fmt == "csv" else reader.json(path)
    else:
        df = spark.read.format(fmt).load(path)
    return TemporalGraph.from_table(df, "src", "dst", "t", eid="eid" if "eid" in df.columns else None, unit=unit)


def write_pair_index(tg, name: str, buckets: int) -> None:
    """A table bucketed by pair and sorted by time: extension joins read it without a shuffle of the edges."""
    tg.edges.select("src", "dst", "t", "eid").write.mode("overwrite").bucketBy(buckets, "src", "dst").sortBy("t").saveAsTable(name)


def write_incidence(tg, name: str, delta: int, buckets: int) -> None:
    """Ranked lists bucketed by (vertex, rank): draws read only the buckets they hit."""
    from tmotif.operators.incidence import ranked_incidence

    ranked_incidence(tg, delta).write.mode("overwrite").bucketBy(buckets, "vertex", "rank").saveAsTable(name)


def write_results(rows: DataFrame, path: str, *partitions: str) -> None:
    rows.write.mode("append").partitionBy(*partitions).parquet(path)
