"""Counts of earlier rows without a single-task window: in-bucket running sums and offsets of whole buckets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tmotif.sources.io import staged

#: Rows that a bucket of the total order should hold.
BUCKET_ROWS = 2_000_000


def counts_below(data: DataFrame, probes: DataFrame, keys: list[str], width: int) -> DataFrame:
    """probes with n: how many rows of data with the same keys have t < x.

    data has keys and t; probes have keys, x and other columns. One shuffle by
    (keys, time bucket) serves the running count; the totals of the buckets, few per key,
    give the offset of each. A hub is thereby cut into as many tasks as it has buckets.
    """
    others = [c for c in probes.columns if c not in (*keys, "x")]
    width = max(1, width)
    rows = data.select(*keys, F.col("t").alias("x"), F.lit(1).alias("one"), *[F.lit(None).cast(probes.schema[c].dataType).alias(c) for c in others])
    both = rows.unionByName(probes.select(*keys, "x", F.lit(0).alias("one"), *others)).withColumn("bucket", F.expr(f"x div {width} - if(x % {width} < 0, 1, 0)"))
    totals = both.groupBy(*keys, "bucket").agg(F.sum("one").alias("held"))
    before = F.coalesce(F.sum("held").over(Window.partitionBy(*keys).orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)) if keys else F.coalesce(F.sum("held").over(Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    offsets = totals.select(*keys, "bucket", before.alias("offset"))
    running = F.sum("one").over(Window.partitionBy(*keys, "bucket").orderBy("x", "one").rowsBetween(Window.unboundedPreceding, Window.currentRow))
    return both.withColumn("run", running).where("one = 0").join(offsets, [*keys, "bucket"]).select(*keys, "x", *others, (F.col("run") + F.col("offset")).cast("bigint").alias("n"))


def ranked(rows: DataFrame, keys: list[str], order: list[str], width: int, name: str = "rank") -> DataFrame:
    """rows with their rank (from 0) among those with the same keys, by order; order[0] is t."""
    width = max(1, width)
    rows = rows.withColumn("bucket", F.expr(f"t div {width} - if(t % {width} < 0, 1, 0)"))
    totals = rows.groupBy(*keys, "bucket").agg(F.count(F.lit(1)).alias("held"))
    offsets = totals.select(*keys, "bucket", F.coalesce(F.sum("held").over(Window.partitionBy(*keys).orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("offset"))
    within = F.row_number().over(Window.partitionBy(*keys, "bucket").orderBy(*order)) - 1
    return rows.withColumn("within", within).join(offsets, [*keys, "bucket"]).withColumn(name, (F.col("within") + F.col("offset")).cast("bigint")).drop("bucket", "within", "offset")


def running_total(rows: DataFrame, value: Column, order: list[str], name: str, buckets: int | None = None) -> DataFrame:
    """rows with the sum of value over all rows before them in the total order, and part, the bucket.

    Buckets are ranges of the whole order (so that many rows of one time are cut, too), dealt by a range
    partitioning and written once, since they are read twice. The offsets are a row for each BUCKET_ROWS rows;
    the plan does not grow with their number.
    """
    rows = rows.withColumn("value_", value)
    if buckets is None:
        buckets = 1 + rows.count() // BUCKET_ROWS
    if buckets == 1:
        rows = rows.withColumn("part", F.lit(0))
    else:
        rows = staged(rows.repartitionByRange(buckets, *order).withColumn("part", F.spark_partition_id()), "ranges")
    within = F.coalesce(F.sum("value_").over(Window.partitionBy("part").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    if buckets == 1:  # one bucket has no offset
        return rows.withColumn(name, within).drop("value_")
    whole = rows.groupBy("part").agg(F.sum("value_").alias("held"))
    offsets = whole.select("part", F.coalesce(F.sum("held").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("offset"))  # a row for each bucket
    return rows.withColumn("within_", within).join(offsets, "part").withColumn(name, F.col("within_") + F.col("offset")).drop("value_", "within_", "offset")


def with_previous(rows: DataFrame, keys: list[str], order: list[str], columns: dict[str, str], back: bool = False) -> DataFrame:
    """rows (with column bucket, whose order agrees with order) and, under new names, columns of the row before each among those of its keys; null if there is none. back: of the row after.

    A key's rows are ordered bucket by bucket; the last row of each bucket, one for each (key, bucket), is carried to the
    next. Column bucket goes.
    """
    sort = [F.col(c).desc() if back else F.col(c) for c in order]
    inner = Window.partitionBy(*keys, "bucket").orderBy(*sort)
    row = F.struct(*order, *[F.col(c).alias(f"{c}_") for c in columns])
    ends = rows.groupBy(*keys, "bucket").agg((F.min if back else F.max)(row).alias("end_"))
    outer = Window.partitionBy(*keys).orderBy(F.col("bucket").desc() if back else F.col("bucket"))
    carried = ends.select(*keys, "bucket", F.lag("end_").over(outer).alias("carry_"))
    first = F.row_number().over(inner) == 1
    found = rows.withColumn("first_", first)
    for c, name in columns.items():
        found = found.withColumn(name, F.lag(c).over(inner))
    on = [F.col(f"r.{c}").eqNullSafe(F.col(f"c.{c}")) for c in (*keys, "bucket")]
    met = found.alias("r").join(carried.alias("c"), on, "left")
    names = [c for c in rows.columns if c != "bucket"]
    return met.select(*[F.col(f"r.{c}").alias(c) for c in names], *[F.when(F.col("first_"), F.col(f"carry_.{c}_")).otherwise(F.col(f"r.{name}")).alias(name) for c, name in columns.items()])


def running_in_keys(rows: DataFrame, keys: list[str], order: list[str], value: str, name: str) -> DataFrame:
    """rows (with column bucket as above) with the sum of value up to and with each row among those of its keys. Column bucket goes."""
    inner = Window.partitionBy(*keys, "bucket").orderBy(*order).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    held = rows.groupBy(*keys, "bucket").agg(F.sum(value).alias("held_"))
    before = Window.partitionBy(*keys).orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    offsets = held.select(*keys, "bucket", F.coalesce(F.sum("held_").over(before), F.lit(0)).alias("offset_"))
    return rows.withColumn("within_", F.sum(value).over(inner)).join(offsets, [*keys, "bucket"]).withColumn(name, F.col("within_") + F.col("offset_")).drop("bucket", "within_", "offset_")
