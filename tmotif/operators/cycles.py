"""Exact counts of directed cycles of three or four edges in time order, by wedges around vertices of low degree.

Vertices are ordered by (degree, vertex). Of a cycle of four the highest vertex names the two that stand beside it as the
centers: the cycle is two wedges around these, which share their ends. Of a cycle of three the lowest vertex is the center,
and an edge between the ends closes the wedge. So each cycle is met once, and a wedge is only formed around a vertex that is lower
than one of its ends (or than both): a hub's edges don't meet each other. Edges that no such wedge can have go before they are
shuffled: those around a vertex without a higher neighbour, and closing edges whose lower end has no lower neighbour.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tmotif.functions.motif import Motif, motif
from tmotif.sources.graph import TemporalGraph
from tmotif.sources.io import staged

#: Vertices that may be broadcast (about 50 MB); more are joined by a shuffle.
BROADCAST_VERTICES = 2_000_000
#: Width of a time bucket, in windows: a wider one has fewer rows at its borders, which stand in two.
WINDOWS = 4


def is_cycle(m: Motif) -> bool:
    """Whether the pattern is a cycle of three or four vertices whose edges follow each other in time."""
    n = len(m.edges)
    return n == len(m.vertices) and n in (3, 4) and all(m.edges[k][1] == m.edges[(k + 1) % n][0] for k in range(n))


def _bucket(t: str, width: int) -> str:
    return f"({t}) div {width} - if(({t}) % {width} < 0, 1, 0)"


def _spread(rows: DataFrame, lo: str, hi: str, width: int) -> DataFrame:
    """Each row in all buckets of the times from lo to hi; none if there is no such time."""
    return rows.where(f"{lo} <= {hi}").withColumn("bucket", F.explode(F.sequence(F.expr(_bucket(lo, width)), F.expr(_bucket(hi, width)))))


def _few(rows: DataFrame) -> DataFrame:
    """A staged table of vertices, broadcast if it may be."""
    return F.broadcast(rows) if rows.count() <= BROADCAST_VERTICES else rows.hint("merge")


def ordered_edges(tg: TemporalGraph) -> DataFrame:
    """src, dst, t of the edges without loops; up, whether dst is the higher end; and for each end x in (src, dst) x_under and x_over: whether it has a lower, and a higher, neighbour."""
    edges = tg.edges.where("src <> dst").select("src", "dst", "t")
    ends = F.explode(F.array("src", "dst")).alias("v")
    degrees = _few(staged(edges.select(ends).groupBy("v").agg(F.count(F.lit(1)).alias("n")), "degrees"))
    for x in ("src", "dst"):
        edges = edges.join(degrees.select(F.col("v").alias(x), F.col("n").alias(f"{x}_n")), x)
    edges = edges.select("src", "dst", "t", F.expr("dst_n > src_n or dst_n = src_n and dst > src").alias("up"))
    sides = F.inline(F.array(F.struct(F.col("src").alias("v"), F.col("up").alias("over")), F.struct(F.col("dst").alias("v"), (~F.col("up")).alias("over"))))
    places = _few(staged(edges.select(sides).groupBy("v").agg(F.max(~F.col("over")).alias("under"), F.max("over").alias("over")), "places"))
    for x in ("src", "dst"):
        edges = edges.join(places.select(F.col("v").alias(x), F.col("under").alias(f"{x}_under"), F.col("over").alias(f"{x}_over")), x)
    return edges


def wedges(into: DataFrame, out: DataFrame, delta: int, both: bool) -> DataFrame:
    """c, u, w, a, b: an edge u -> c at a and one c -> w at b, not at the same time and at most delta apart, with an end (or both ends) higher than c.

    into and out: c, end, t, high of edges to and from their centers.
    """
    width = max(1, WINDOWS * delta)
    into = _spread(into.select("c", F.col("end").alias("u"), F.col("t").alias("a"), F.col("high").alias("high_u")), f"a - {delta}", f"a + {delta}", width)
    out = out.select("c", F.col("end").alias("w"), F.col("t").alias("b"), F.col("high").alias("high_w"), F.expr(_bucket("t", width)).alias("bucket"))
    high = "high_u and high_w" if both else "(high_u or high_w)"
    return into.hint("merge").join(out, ["c", "bucket"]).where(f"u <> w and a <> b and abs(a - b) <= {delta} and {high}").select("c", "u", "w", "a", "b")


def _roles(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Edges to and from centers that have a higher neighbour."""
    into = edges.where("dst_over").select(F.col("dst").alias("c"), F.col("src").alias("end"), "t", (~F.col("up")).alias("high"))
    return into, edges.where("src_over").select(F.col("src").alias("c"), F.col("dst").alias("end"), "t", F.col("up").alias("high"))


def _fours(edges: DataFrame, delta: int) -> DataFrame:
    found = staged(wedges(*_roles(edges), delta, both=False), "wedges")
    width = max(1, WINDOWS * delta)
    # the later two edges of the cycle, or the middle two: one after the other around their center
    second = found.where("a < b").select(F.col("c").alias("d"), F.col("u").alias("w"), F.col("w").alias("u"), F.col("a").alias("x"), F.col("b").alias("y"), F.expr(_bucket("a", width)).alias("bucket"))
    # the first two edges, so that the others come after both; or the first and the last one, so that the others come between
    first = found.select("c", "u", "w", "b", F.expr(f"if(a < b, a + {delta}, a - 1)").alias("until"))
    first = _spread(first.withColumn("from", F.expr("b + 1")).withColumn("last", F.expr("until - 1")), "from", "last", width)
    return first.hint("merge").join(second, ["u", "w", "bucket"]).where("c <> d and x > b and y <= until").agg(F.count(F.lit(1)).alias("count"))


def _threes(edges: DataFrame, delta: int) -> DataFrame:
    closing = staged(edges.where("if(up, src_under, dst_under)").select("src", "dst", "t"), "closing")
    ends = _few(staged(closing.select(F.explode(F.array("src", "dst")).alias("end")).distinct(), "ends"))
    into, out = (x.where("high").join(ends, "end", "left_semi") for x in _roles(edges))
    width = max(1, WINDOWS * delta)
    found = wedges(into, out, delta, both=True).withColumn("from", F.expr(f"if(a < b, b - {delta}, b + 1)")).withColumn("until", F.expr(f"if(a < b, a + {delta}, a - 1)"))
    own = closing.select(F.col("src").alias("w"), F.col("dst").alias("u"), F.col("t").alias("q"), F.expr(_bucket("t", width)).alias("bucket"))
    fits = "q between from and until and (a > b or q < a or q > b)"
    return _spread(found, "from", "until", width).hint("merge").join(own, ["u", "w", "bucket"]).where(fits).agg(F.count(F.lit(1)).alias("count"))


def cycle_count(tg: TemporalGraph, which: str | Motif, delta: int) -> DataFrame:
    """One row, count: the matches of a cycle (see is_cycle), in strictly increasing times within delta."""
    m = motif(which)
    if not is_cycle(m):
        raise ValueError("the pattern is no cycle of three or four edges in time order")
    return (_threes if len(m.edges) == 3 else _fours)(ordered_edges(tg), delta)
