"""What SQL users get: table functions over the catalogue, chain counts, the error measure."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from tmotif.functions.motif import CATALOG


@udtf(returnType="pos int, src string, dst string")
class MotifEdges:
    def eval(self, name: str):
        for p, (a, b) in enumerate(CATALOG[name].edges):
            yield p, a, b


@udtf(returnType="anchor string, class string")
class MotifAnchors:
    def eval(self, name: str):
        for a in CATALOG[name].anchors():
            yield ",".join(map(str, a.positions)), str(a.cls)


@udtf(returnType="k bigint")
class MotifSampleBound:
    def eval(self, sigma: float, r: int, w: float, c: float, eps: float, gamma: float):
        from tmotif.plans.estimate import required_samples

        yield (required_samples(float(sigma), r, float(w), float(c), float(eps), float(gamma)),)


def register(spark: SparkSession) -> None:
    """motif_edges, motif_anchors, motif_sample_bound (table functions), chain_count (scalar over arrays in scan order), chain_total (aggregate), rel_error."""
    from tmotif.operators.extend import chain_count, chain_total

    spark.udtf.register("motif_edges", MotifEdges)
    spark.udtf.register("motif_anchors", MotifAnchors)
    spark.udtf.register("motif_sample_bound", MotifSampleBound)
    spark.udf.register("chain_count", chain_count)
    spark.udf.register("chain_total", chain_total)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION rel_error(c DOUBLE, e DOUBLE) RETURN abs(c - e) / nullif(c, 0)")


def catalog_table(spark: SparkSession) -> DataFrame:
    rows = [(m.name, p, a, b) for m in CATALOG.values() for p, (a, b) in enumerate(m.edges)]
    return spark.createDataFrame(rows, "motif string, pos int, src string, dst string")
