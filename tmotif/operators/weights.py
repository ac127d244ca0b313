"""Weights of centers: how many paths or wedges of a class have an edge in the middle."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tmotif.functions.motif import PathClass, WedgeClass
from tmotif.operators.incidence import class_ends, windowed_degrees
from tmotif.operators.prefix import running_total
from tmotif.sources.graph import TemporalGraph


def weights(tg: TemporalGraph, delta: int, cls: PathClass | WedgeClass, impl: str = "sweep", ties: str = "strict") -> DataFrame:
    """Edges with their windowed degrees and w, the product of these."""
    out = windowed_degrees(tg, delta, cls, impl, ties)
    w = F.col("n1") * F.col("n3") if isinstance(cls, PathClass) else F.col("n1")
    return out.withColumn("w", w)


def static_weights(tg: TemporalGraph, cls: PathClass | WedgeClass) -> DataFrame:
    """Weights of the ablation without time: whole degrees in place of windowed ones."""
    out = tg.edges.select("eid", "src", "dst", "t")
    for k, end, sign, _ in class_ends(cls):
        degree = tg.edges.groupBy(F.col("src" if sign == "+" else "dst").alias(end)).agg(F.count(F.lit(1)).alias(f"n{k}"))
        out = out.join(degree, end, "left").withColumn(f"n{k}", F.coalesce(f"n{k}", F.lit(0).cast("bigint"))).withColumn(f"lo{k}", F.lit(0).cast("bigint"))
    w = F.col("n1") * F.col("n3") if isinstance(cls, PathClass) else F.col("n1")
    return out.select("eid", "src", "dst", "t", *[f"{x}{k}" for k, *_ in class_ends(cls) for x in ("lo", "n")], w.alias("w"))


def total(weighted: DataFrame) -> int:
    """W, over decimals so that it may pass 2^63."""
    return int(weighted.agg(F.sum(F.col("w").cast("decimal(38,0)"))).first()[0] or 0)


def with_offsets(weighted: DataFrame, order: list[str] | None = None, buckets: int | None = None) -> DataFrame:
    """Centers of positive weight with first, the number of paths before theirs in (t, eid) order."""
    return running_total(weighted.where("w > 0"), F.col("w").cast("decimal(38,0)"), order or ["t", "eid"], "first", buckets)


def probabilities(weighted: DataFrame) -> DataFrame:
    """Adds p = w / W (null if W is 0)."""
    whole = weighted.agg(F.sum(F.col("w").cast("decimal(38,0)")).alias("whole"))
    return weighted.crossJoin(F.broadcast(whole)).withColumn("p", F.when(F.col("whole") > 0, F.col("w") / F.col("whole").cast("double"))).drop("whole")  # one row


def degree_table(tg: TemporalGraph, delta: int) -> DataFrame:
    """eid and eight windowed degrees: n1.. at the source and n3.. at the target, for each sign and side."""
    wide = None
    for sign in "-+":
        for side in "<>":
            one = windowed_degrees(tg, delta, PathClass(sign, sign, side, side)).select("eid", F.lit(sign + side).alias("kind"), "n1", "n3")
            wide = one if wide is None else wide.union(one)
    return wide.groupBy("eid").agg(*[F.max(F.when(F.col("kind") == s + b, F.col(n))).alias(f"{n}{s}{b}") for s in "-+" for b in "<>" for n in ("n1", "n3")])


def _class_weight(cls: PathClass | WedgeClass):
    if isinstance(cls, PathClass):
        return F.col(f"n1{cls.a1}{cls.b1}") * F.col(f"n3{cls.a3}{cls.b3}")
    return F.col(f"{'n1' if cls.pivot == 'src' else 'n3'}{cls.a}{cls.b}")


def all_weights(tg: TemporalGraph, delta: int, classes: list | None = None) -> DataFrame:
    """class, eid, w for several classes (default: the 16 of paths) from one table of degrees."""
    cells = [F.struct(F.lit(str(c)).alias("class"), _class_weight(c).alias("w")) for c in classes or PathClass.all()]
    return degree_table(tg, delta).select("eid", F.inline(F.array(*cells))).select("class", "eid", "w")


def totals(tg: TemporalGraph, delta: int, classes: list | None = None) -> DataFrame:
    """class, w_total for several classes."""
    return all_weights(tg, delta, classes).groupBy("class").agg(F.sum("w").cast("bigint").alias("w_total"))
