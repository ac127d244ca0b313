"""Paths by number. Centers in (t, eid) order own consecutive numbers, as many as their weight;
number o of a center is the pair (o div n3, o mod n3) of its end edges. Drawing a number
uniformly draws a path uniformly; taking all numbers lists all paths.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tmotif.functions.motif import PathClass, WedgeClass
from tmotif.operators.incidence import class_ends, ranked_incidence
from tmotif.sources.graph import TemporalGraph
from tmotif.sources.io import staged

#: Draws of at most so many rows are broadcast to the incidence lists.
BROADCAST_DRAWS = 1_000_000
BITS = 52


def _hash(text) -> object:
    """The first 52 bits of the MD5 of a text."""
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 13), 16, 10).cast("decimal(20,0)")


def draws(spark: SparkSession, k: int, total: int, seed: int | Sequence[int] = 42, scheme: str = "iid", first: int = 0) -> DataFrame:
    """draw, path_id: k numbers below total, a pure function of (seed, draw).

    iid: independent. stratified: draw i from the i-th of k equal ranges.
    without_replacement: i.i.d. draws without repeats (fewer rows than k may come back).
    Of several seeds (iid only) the i-th has the draws from i * k on, each the same as in a run of its own.
    """
    if k <= 0:
        raise ValueError("k is at least 1")
    if total == 0:
        return spark.range(0).select(F.col("id").alias("draw"), F.lit(0).cast("decimal(38,0)").alias("path_id"))
    if total >= 1 << 60:  # h * total would pass 38 digits
        raise ValueError("W is beyond 2^60; split the graph in time")
    rows = spark.range(first, first + k).select(F.col("id").alias("draw"))
    named = F.concat(F.lit(f"{seed}|"), F.col("draw").cast("string"))
    if not isinstance(seed, int):
        if scheme != "iid":
            raise ValueError("several seeds are for independent draws")
        seeds = [*seed]
        rows = spark.range(first, first + k * len(seeds)).select(F.col("id").alias("draw"))
        nth = F.expr(f"(draw - {first}) div {k}")
        named = F.concat(F.get(F.array(*map(F.lit, seeds)), nth).cast("string"), F.lit("|"), (F.col("draw") - nth * k).cast("string"))
    h = _hash(named)
    if scheme == "stratified":
        low = F.expr(f"cast((cast(draw as decimal(20,0)) - {first}) * {total} div {k} as decimal(38,0))")
        high = F.expr(f"cast((cast(draw as decimal(20,0)) - {first} + 1) * {total} div {k} as decimal(38,0))")
        return rows.withColumn("h", h).withColumn("low", low).withColumn("size", F.greatest(high - F.col("low"), F.lit(1))).select("draw", (F.col("low") + F.expr(f"cast(h * cast(size as decimal(18,0)) div {1 << BITS} as decimal(38,0))")).cast("decimal(38,0)").alias("path_id"))
    out = rows.withColumn("h", h).select("draw", F.expr(f"cast(h * cast({total} as decimal(18,0)) div {1 << BITS} as decimal(38,0))").alias("path_id"))
    if scheme == "without_replacement":
        return out.groupBy("path_id").agg(F.min("draw").alias("draw")).select("draw", "path_id")
    if scheme != "iid":
        raise ValueError(f"unknown scheme {scheme}")
    return out


def poisson_draws(weighted: DataFrame, k: int, total: int, seed: int = 42) -> DataFrame:
    """Centers with offsets, drawn w * k / W times in expectation: the whole part, and one more by hash. Written once, since draws are numbered here."""
    rate = F.col("w").cast("double") * k / total
    u = _hash(F.concat(F.lit(f"{seed}|"), F.col("eid").cast("string"))).cast("double") / (1 << BITS)
    times = (F.floor(rate) + (u < rate - F.floor(rate)).cast("int")).cast("int")
    hit = weighted.withColumn("times", times).where("times > 0").select("*", F.explode(F.sequence(F.lit(1), F.col("times"))).alias("nth"))
    hit = hit.withColumn("h", _hash(F.concat(F.lit(f"{seed}|"), F.col("eid").cast("string"), F.lit("|"), F.col("nth").cast("string"))))
    hit = hit.withColumn("o", F.expr(f"cast(h * cast(w as decimal(18,0)) div {1 << BITS} as bigint)"))
    return staged(hit.withColumn("path_id", F.col("first") + F.col("o")).withColumn("draw", F.monotonically_increasing_id()).drop("times", "nth", "h"), "draws")


def locate(drawn: DataFrame, centers: DataFrame, k: int) -> DataFrame:
    """Draws with their center's columns and o, the number within the center; k: how many draws.

    An equi-join on cells of numbers. Cells of level l are 2^l times as wide as a center is on average, and a center lies in
    cells of its own size, three at most; a draw asks each level, of which there are as many as the largest weight
    has bits above the average. Centers are only read, not sorted or shuffled, where draws are few enough to be broadcast.
    """
    names = [c for c in centers.columns if c != "part"]
    row = centers.agg(F.count(F.lit(1)).alias("n"), F.max("w").alias("w"), F.max(F.col("first") + F.col("w")).alias("whole")).first()
    if not row["n"]:
        return drawn.where("false").select("draw", "path_id", *[F.lit(None).cast(centers.schema[c].dataType).alias(c) for c in names], F.lit(0).cast("bigint").alias("o"))
    step = max(1, int(row["whole"]) // row["n"])
    levels = max(0, (int(row["w"]) // step).bit_length())
    level = F.least(F.greatest(F.ceil(F.log2(F.col("w").cast("double") / step)), F.lit(0)), F.lit(levels)).cast("int")
    size = F.call_function("shiftleft", F.lit(step).cast("bigint"), F.col("level"))
    start = F.col("first").cast("bigint")
    owned = centers.select(*names).withColumn("level", level).withColumn("cell", F.explode(F.sequence(F.call_function("div", start, size), F.call_function("div", start + F.col("w") - 1, size))))
    asked = drawn.withColumn("number", F.col("path_id").cast("bigint"))
    asked = asked.select("draw", "path_id", "number", F.inline(F.array(*[F.struct(F.lit(x).alias("level"), F.expr(f"number div {step << x}").alias("cell")) for x in range(levels + 1)])))
    if k * (levels + 1) <= BROADCAST_DRAWS:
        asked = F.broadcast(asked)
    found = owned.join(asked, ["level", "cell"]).where((F.col("number") >= start) & (F.col("number") < start + F.col("w")))
    return found.select("draw", "path_id", *names, (F.col("number") - start).alias("o"))


def every_path(centers: DataFrame, cls: PathClass | WedgeClass) -> DataFrame:
    """All numbers of all centers: rows with o, draw and path_id, W of them."""
    spread = centers.where("w > 0").withColumn("o1", F.explode(F.expr("sequence(0L, n1 - 1)")))
    if isinstance(cls, PathClass):
        spread = spread.withColumn("o3", F.explode(F.expr("sequence(0L, n3 - 1)"))).withColumn("o", F.col("o1") * F.col("n3") + F.col("o3")).drop("o3")
    else:
        spread = spread.withColumn("o", F.col("o1"))
    number = (F.col("first") + F.col("o")).cast("decimal(38,0)")
    return spread.drop("o1").select("*", number.cast("bigint").alias("draw"), number.alias("path_id"))


def decode(located: DataFrame, lists: DataFrame, cls: PathClass | WedgeClass, few: bool = False, many: bool = False) -> DataFrame:
    """draw, path_id, eid1, eid2(, eid3), t1, t2(, t3), v0..: the edges behind the numbers.

    many: located has far more rows than the table it is made of, whose size the planner takes for its own, so that it must not be broadcast.
    Of a path edge 2 is the center and v1 -> v2; of a wedge edge 1 is the base v0 -> v1 and edge 2 the other, v2 its far end.
    """
    path = isinstance(cls, PathClass)
    out = located.withColumn("r1", F.expr("lo1 + o div n3") if path else F.col("lo1") + F.col("o"))
    if path:
        out = out.withColumn("r3", F.expr("lo3 + o % n3"))
    out = out.withColumnsRenamed({"eid": "ceid", "t": "ct"})
    for k, end, sign, _ in class_ends(cls):
        own = lists.where(F.col("dir") == sign).select(F.col("vertex").alias(end), F.col("rank").alias(f"r{k}"), F.col("t").alias(f"et{k}"), F.col("eid").alias(f"ee{k}"), F.col("other").alias(f"o{k}"))
        out = own.join(F.broadcast(out) if few else out.hint("merge") if many else out, [end, f"r{k}"])
    if path:
        return out.select("draw", "path_id", F.col("ee1").alias("eid1"), F.col("ceid").alias("eid2"), F.col("ee3").alias("eid3"), F.col("et1").alias("t1"), F.col("ct").alias("t2"), F.col("et3").alias("t3"), F.col("o1").alias("v0"), F.col("src").alias("v1"), F.col("dst").alias("v2"), F.col("o3").alias("v3"))
    return out.select("draw", "path_id", F.col("ceid").alias("eid1"), F.col("ee1").alias("eid2"), F.col("ct").alias("t1"), F.col("et1").alias("t2"), F.col("src").alias("v0"), F.col("dst").alias("v1"), F.col("o1").alias("v2"))


def sample_paths(tg: TemporalGraph, centers: DataFrame, total: int, delta: int, cls: PathClass | WedgeClass, k: int, seed: int | Sequence[int] = 42, scheme: str = "iid", first: int = 0, lists: DataFrame | None = None) -> DataFrame:
    """Drawn paths; lists: the ranked incidence, if it is there already."""
    spark = tg.edges.sparkSession
    lists = ranked_incidence(tg, delta) if lists is None else lists
    if scheme == "poisson":
        return decode(poisson_draws(centers, k, max(total, 1), seed), lists, cls, few=2 * k + 1000 <= BROADCAST_DRAWS)
    n = k if isinstance(seed, int) else k * len([*seed])
    return decode(locate(draws(spark, k, total, seed, scheme, first), centers, n), lists, cls, few=n <= BROADCAST_DRAWS)


def list_paths(tg: TemporalGraph, centers: DataFrame, delta: int, cls: PathClass | WedgeClass, lists: DataFrame | None = None) -> DataFrame:
    return decode(every_path(centers, cls), ranked_incidence(tg, delta) if lists is None else lists, cls, many=True)
