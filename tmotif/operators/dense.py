"""Exact counts where a few vertices share very many edges: all ways to place the pattern's vertices at once, chains by running sums.

Time is cut into buckets as wide as the window. Of a first edge in a bucket, the window ends in the next one, so that a
chain is a part in the bucket after that edge and a part in the next bucket. Both are running sums over the
distinct times at which the placing has an edge, a column for each placing of the vertices; no path and no match is ever a row. Work is
such times x placings x the square of the pattern's edges, whatever the counts.
"""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tmotif.functions.motif import Motif, PathClass, WedgeClass
from tmotif.operators.incidence import class_ends
from tmotif.sources.graph import TemporalGraph
from tmotif.sources.io import staged, workers_see_package

#: Paths beyond which counts are made here, if the graph has at most VERTICES and a bucket's table at most CELLS.
MANY, VERTICES, CELLS = 2_000_000, 32, 1 << 26
#: Numbers in one array of running sums.
CHUNK = 1 << 17
SCHEMA = "valid string, hits string, found string, squares string, most bigint"


def leading(m: Motif) -> int | None:
    """How many first edges the motif's anchor consists of; None if it is not made of the first ones."""
    n = len(m.anchor().positions) if m.anchors() else 0
    return n if n and set(m.anchor().positions) == set(range(n)) else None


def _floor(width: int) -> str:
    return f"t div {width} - if(t % {width} < 0, 1, 0)"


def may_be_dense(tg: TemporalGraph, m: Motif) -> bool:
    """Whether the vertices are few and the anchor holds the first edges."""
    return leading(m) is not None and len(tg.vertices().limit(VERTICES + 1).collect()) <= VERTICES


def paths_at_most(tg: TemporalGraph, delta: int, cls: PathClass | WedgeClass) -> int:
    """A bound on W: the degrees are those in the whole buckets that a center's window meets, so that no edge is sorted or ranked."""
    pairs = tg.edges.groupBy(F.expr(_floor(delta)).alias("bucket"), "src", "dst").agg(F.count(F.lit(1)).alias("n"))
    product = F.col("n").cast("decimal(38,0)")
    out = pairs
    for k, end, sign, side in class_ends(cls):
        reached = F.explode(F.array("bucket", F.col("bucket") + (1 if side == "<" else -1))).alias("bucket")
        own = pairs.select(reached, F.col("src" if sign == "+" else "dst").alias(end), "n")
        out = out.join(own.groupBy("bucket", end).agg(F.sum("n").alias(f"n{k}")), ["bucket", end])
        product = product * F.col(f"n{k}")
    return int(out.agg(F.sum(product.cast("decimal(38,0)"))).first()[0] or 0)


def is_dense(tg: TemporalGraph, m: Motif, delta: int, w_total: int | None = None) -> bool:
    """Whether the paths of the motif's anchor are too many to be listed and the graph small enough for tables of all placings. w_total: the paths, if known; else a bound on them is taken."""
    if delta < 1 or w_total is None and not may_be_dense(tg, m):
        return False
    if (paths_at_most(tg, delta, m.anchor().cls) if w_total is None else w_total) <= MANY:
        return False
    times = tg.edges.groupBy(F.expr(_floor(delta)).alias("bucket")).agg(F.countDistinct("t").alias("n")).agg(F.max("n")).first()[0] or 0
    return 2 * times * VERTICES * VERTICES <= CELLS


def _after(column: np.ndarray) -> np.ndarray:
    """Sums of the rows after each; nothing is subtracted, so that doubles keep their relative error."""
    out = np.zeros_like(column)
    out[:-1] = np.cumsum(column[:0:-1], axis=0)[::-1]
    return out


def _before(column: np.ndarray) -> np.ndarray:
    """Sums of the rows before each place, a place more than rows."""
    return np.concatenate([np.zeros((1, *column.shape[1:]), column.dtype), np.cumsum(column, axis=0)])


def chains(cells: list[np.ndarray], n: int, ends: np.ndarray) -> np.ndarray:
    """Chains that begin with cells[0] in each of the first n rows and go on through the other cells in later rows before the place in ends (n or more; of each row, or of each cell)."""
    length = len(cells)
    # here[j]: chains of the positions i..j-1 in the first n rows after each; i falls to 1
    here: dict[int, np.ndarray] = {length: np.ones_like(cells[0][:n])}
    for i in range(length - 1, 0, -1):
        here = {j: _after(cells[i][:n] * x) for j, x in here.items()} | {i: np.ones_like(cells[0][:n])}
    out = here[length]
    for j in range(1, length):
        then = np.ones((len(cells[0]) - n + 1, *cells[0].shape[1:]), cells[0].dtype)
        for q in range(j, length):
            then = _before(cells[q][n:] * then[:-1])
        out = out + here[j] * (then[ends - n] if ends.ndim == 1 else np.take_along_axis(then, ends - n, axis=0))
    return out * cells[0][:n]


def _closed_up(active: np.ndarray) -> np.ndarray:
    """Of each column the rows that are active, in order; columns with fewer than the most are filled up with the number of rows."""
    column, row = np.nonzero(active.T)
    sizes = np.bincount(column, minlength=active.shape[1])
    out = np.full((int(sizes.max(initial=0)), active.shape[1]), len(active))
    out[np.arange(len(row)) - np.repeat(np.cumsum(sizes) - sizes, sizes), column] = row
    return out


def own_rows(table: np.ndarray, spots: list[np.ndarray], n: int, ends: np.ndarray) -> tuple[list[np.ndarray], int, np.ndarray]:
    """Cells, n and ends for chains(), a column for each placing, with only those rows of the table in which the placing has an edge; rows of zeros fill up.

    table ends with a row of zeros beyond its times.
    """
    rows = len(table) - 1
    full = table[:rows] != 0
    active = np.zeros((rows, len(spots[0])), bool)
    for s in spots:
        active |= full[:, s]
    first, then = _closed_up(active[:n]), _closed_up(active[n:])
    at = np.concatenate([np.where(first == n, rows, first), then + n])
    place = np.concatenate([np.zeros((1, active.shape[1]), np.int64), np.cumsum(active[n:], axis=0)])
    stops = np.take_along_axis(place, ends[np.minimum(first, n - 1)] - n, axis=0) if n else first
    return [table[at, s] for s in spots], len(first), stops + len(first)


def _most(sizes: list[int]) -> int:
    """A bound on the chains through positions of so many edges."""
    return min(math.prod(sizes), math.comb(sum(sizes), len(sizes)) if len(sizes) else 1)


def _whole(low: int, near: float, apart: float) -> int | None:
    """The number with the lowest 64 bits of low that is at most apart from near; None if apart does not single one out."""
    if not apart < 2.0**62:
        return None
    low %= 1 << 64
    return low + ((int(near) - low + (1 << 63)) >> 64 << 64)


def all_chains(cells: list[np.ndarray], n: int, ends: np.ndarray, bound: int) -> int:
    """Sum of chains(), exact; bound: none of the sums passes it.

    Beyond 62 bits the lowest 64 come from sums that wrap around, the others from doubles. No term is negative and none is subtracted, so that
    a double is off by its own share of the roundings alone. Where that is too much, in Python's integers.
    """
    with np.errstate(over="ignore"):
        low = int(chains(cells, n, ends).sum())
    if bound < 1 << 62:
        return low
    near = float(chains([c.astype(np.float64) for c in cells], n, ends).sum())
    steps = (2 * len(cells) + 2) * (len(cells[0]) + 2) + cells[0].size
    found = _whole(low, near, near * steps * 2.0**-52)
    return int(chains([c.astype(object) for c in cells], n, ends).sum()) if found is None else found


def _hits(cells: list[np.ndarray], first: int, n: int, ends: np.ndarray) -> np.ndarray:
    """Starts of such chains: ways to take the first positions so that some chain goes through the rest."""
    rows, wide = cells[0].shape
    last = np.broadcast_to(ends[:, None], (n, wide)).copy()
    for c in cells[:first - 1:-1]:
        place = np.concatenate([np.full((1, wide), -1), np.maximum.accumulate(np.where(c != 0, np.arange(rows)[:, None], -1), axis=0)])
        last = np.maximum(np.take_along_axis(place, last, axis=0), 0)
    at = np.arange(1, n + 1)[:, None]
    last = np.maximum(last, at)
    one = _before(cells[1])
    take = lambda x: np.take_along_axis(x, last, axis=0)
    if first == 2:
        x = take(one) - one[at[:, 0]]
    else:
        both, two = _before(cells[2] * one[:-1]), _before(cells[2])
        x = take(both) - both[at[:, 0]] - one[at[:, 0]] * (take(two) - two[at[:, 0]])
    return x * cells[0][:n]


#: Primes below 2^31: the residues of a sum by them and by 2^64 name it.
PRIMES = (2147483647, 2147483629, 2147483587, 2147483579)


def _residue(own: list[np.ndarray], first: int, starts: np.ndarray, far: np.ndarray, prime: int | None) -> int:
    """Sum of the squares of what completes each anchor, by a prime or (None) by 2^64.

    The completions of an anchor from s to e are a sum of products f(s) g(e), and so is their square; over all e from s to far they are differences of running sums.
    """
    by = (lambda x: x) if prime is None else (lambda x: x % prime)
    c, one = own[first - 1], _before(own[first])
    if len(own) - first == 1:
        f, g = [one[far], np.ones_like(far)], [np.ones_like(c), -one[1:]]
    else:
        both, two = _before(own[first + 1] * one[:-1]), _before(own[first + 1])
        f, g = [both[far], -two[far], np.ones_like(far)], [np.ones_like(c), one[1:], one[1:] * two[1:] - both[1:]]
    f, g = [by(x) for x in f], [by(x) for x in g]
    mid = by(_before(own[1])) if first == 3 else None
    out, after = 0, starts + 1
    for k in range(len(f)):
        for j in range(len(f)):
            x = by(c * by(g[k] * g[j]))
            till = lambda y: by(y[far] - y[np.minimum(after, far)])
            inner = till(_before(x))
            if mid is not None:
                inner = by(till(_before(by(x * mid[:-1]))) - by(mid[after] * inner))
            out += int(by(by(f[k] * f[j]) * by(own[0][starts] * inner)).sum())
    return out % (prime or 1 << 64)


def _spread(cells: list[np.ndarray], first: int, n: int, ends: np.ndarray) -> tuple[int, int]:
    """Sum of the squares and the largest of the chains that complete each anchor; one or two positions are free. Work is the rows, not their pairs; ends: of each cell."""
    squares, most = 0, 0
    for a in range(cells[0].shape[1]):
        own = [np.ascontiguousarray(c[:, a]) for c in cells]
        starts = np.flatnonzero(own[0][:n])
        far = ends[starts, a]
        # the sooner an anchor ends, the more completes it
        stop = starts
        for c in own[1:first]:
            at = np.append(np.flatnonzero(c), len(c))
            stop = at[np.searchsorted(at, np.minimum(stop + 1, len(c)))]
        fits = stop < far
        starts, far, stop = starts[fits], far[fits], stop[fits]
        if not len(starts):
            continue
        one = _before(own[first])
        x = one[far] - one[stop + 1]
        if len(own) - first == 2:
            both, two = _before(own[first + 1] * one[:-1]), _before(own[first + 1])
            x = both[far] - both[stop + 1] - one[stop + 1] * (two[far] - two[stop + 1])
        high = int(x.max())
        if not high:
            continue
        most = max(most, high)
        bound = high**2 * math.prod(int(c.sum()) for c in own[:first])
        with np.errstate(over="ignore"):
            found, modulus = _residue(own, first, starts, far, None), 1 << 64
        for prime in PRIMES:
            if bound < modulus:
                break
            found += modulus * ((_residue(own, first, starts, far, prime) - found) * pow(modulus, -1, prime) % prime)
            modulus *= prime
        if bound >= modulus:
            raise OverflowError("the squares of completions pass 188 bits")
        squares += found
    return squares, most


def _placings(m: Motif, v: int) -> list[np.ndarray]:
    """Columns of the pair table for each pattern edge, a number for each way to place the vertices."""
    grid = np.indices((v,) * len(m.vertices)).reshape(len(m.vertices), -1)
    apart = np.ones(grid.shape[1], bool)
    for i in range(len(grid)):
        for j in range(i):
            apart &= grid[i] != grid[j]
    at = dict(zip(m.vertices, grid[:, apart], strict=True))
    return [at[a] * v + at[b] for a, b in m.edges]


def _counted(m: Motif, delta: int, first: int, paths: bool, spread: bool) -> Callable[[tuple, pa.Table], pa.Table]:
    def count(key: tuple, rows: pa.Table) -> pa.Table:
        t, ends_of = rows["t"].to_numpy(), np.concatenate([rows["src"].to_numpy(), rows["dst"].to_numpy()])
        names, vertex = np.unique(ends_of, return_inverse=True)
        v, middle = len(names), (key[0].as_py() + 1) * delta
        times, row = np.unique(t, return_inverse=True)
        n = int(np.searchsorted(times, middle))
        table = np.bincount(row * v * v + vertex[: len(t)] * v + vertex[len(t) :], minlength=len(times) * v * v).reshape(len(times), v * v)
        ends = np.searchsorted(times, times[:n] + delta, "right")
        held, begun = table.sum(axis=0), table[:n].sum(axis=0)
        spots = _placings(m, v)
        alive = begun[spots[0]] > 0
        for p in range(1, first):
            alive &= held[spots[p]] > 0
        # placings with about as many edges go together, so that few rows are filled up
        alive = np.flatnonzero(alive)
        alive = alive[np.argsort(sum(held[s[alive]] for s in spots), kind="stable")]
        spots = [s[alive] for s in spots]
        padded = np.concatenate([table, np.zeros((1, v * v), table.dtype)])
        sums, most = [0, 0, 0, 0], 0
        step = max(1, CHUNK // len(times))
        for k in range(0, len(spots[0]), step):
            some = [s[k : k + step] for s in spots]
            if paths:
                sums[0] += int(chains(*own_rows(padded, some[:first], n, ends)).sum())
            whole = np.all([held[s] > 0 for s in some], axis=0)
            some = [s[whole] for s in some]
            if not len(some[0]):
                continue
            cells, begin, stops = own_rows(padded, some, n, ends)
            bound = _most([int(held[s].max()) for s in some]) * len(some[0])
            sums[2] += all_chains(cells, begin, stops, bound)
            if spread:
                square, high = _spread(cells, first, begin, stops)
                sums[3] += square
                most = max(most, high)
            if paths:
                sums[1] += int(_hits([table[:, s] for s in some], first, n, ends).sum())
        return pa.table({k: pa.array([str(x)]) for k, x in zip(("valid", "hits", "found", "squares"), sums, strict=True)} | {"most": pa.array([most], pa.int64())})

    return count


def fitting(rows: DataFrame, *columns: str) -> DataFrame:
    """The rows, written once; each of the columns, counts, is bigint if all its values fit, else decimal(38,0)."""
    rows = staged(rows, "counts")
    most = rows.agg(*[F.max(c).alias(c) for c in columns]).first()
    return rows.withColumns({c: F.col(c).cast("bigint" if (most[c] or 0) < 1 << 63 else "decimal(38,0)") for c in columns})


def dense_counts(tg: TemporalGraph, m: Motif, delta: int, paths: bool = False, spread: bool = False) -> DataFrame:
    """One row of decimals: found, the matches; with paths also valid and hits, the anchor's valid paths and those that are completed; with spread also squares and most, of the completions of each."""
    first, width = leading(m), max(1, delta)
    if spread and not 1 <= len(m.edges) - first <= 2:
        raise ValueError("spread is for one or two free edges")
    workers_see_package(tg.edges.sparkSession)
    own = F.expr(_floor(width))
    rows = tg.edges.where("src <> dst").select("src", "dst", "t", F.explode(F.array(own, own - 1)).alias("bucket"))
    parts = rows.groupBy("bucket").applyInArrow(_counted(m, width, first, paths, spread), SCHEMA)
    number = lambda c: F.coalesce(F.sum(F.col(c).cast("decimal(38,0)")), F.lit(0).cast("decimal(38,0)")).alias(c)
    return parts.agg(*map(number, ("valid", "hits", "found", "squares")), F.coalesce(F.max("most"), F.lit(0)).cast("bigint").alias("most"))
