"""SimHash near-dedup with pigeonring filtering.

A fingerprint's 64 bits lie on a ring of m equal segments. If two fingerprints
differ in at most t bits, then some segment starts a chain in which every prefix
of l segments differs in at most floor(l * t / m) bits. While l * t < m that
budget is zero, so the first such segments must be equal: they are the join
key, with the start as a part of it. Pairs that meet there must keep to the
budgets of all longer chains before the full Hamming distance is taken.

Equal fingerprints are one node from the start. Keys with more than CROWD
fingerprints do not form pairs. There, for t <= 2, each fingerprint goes to its
65 midpoints (itself and each one-bit change): two fingerprints are within two
bits exactly if they share a midpoint, and all that share one are within two
bits of each other, so a star at each midpoint links the same components with
a number of rows that is linear in the crowd. For other t pairs are formed.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tmotif.llm.common import components, in_arrow, marked, numbered, shuffled, staged, text_table, without, workers_see_package

SEGMENTS = 16
CROWD = 64
#: Fixed value: upper-case ASCII letters to lower case, other bytes as they are.
LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


def _bits(hashes: np.ndarray) -> int:
    """Signed 64-bit fingerprint: a bit is set if it is in over half of the hashes."""
    ones = np.zeros(64, np.int64)
    for k in range(0, len(hashes), 1 << 15):
        ones += np.unpackbits(hashes[k : k + (1 << 15)].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int(np.packbits(ones * 2 > len(hashes)).view(">i8")[0])


def fingerprint(text: bytes, width: int, seed: int = 42) -> int:
    """Of the word shingles with repeats; a text of fewer words is one shingle, one without words is zero."""
    words = text.translate(LOWER).split()  # bytes.split() parts at the six ASCII white space characters
    if not words:
        return 0
    line = b" ".join(words)
    n = len(words) - width + 1
    if n < 2:
        return int(np.uint64(xxhash.xxh64_intdigest(line, seed)).astype(np.int64))
    ends = np.cumsum([len(w) + 1 for w in words])
    starts = [0, *ends[: n - 1].tolist()]
    digest = xxhash.xxh64_intdigest
    return _bits(np.array([digest(line[a:b], seed) for a, b in zip(starts, (ends[width - 1 :] - 1).tolist(), strict=True)], np.uint64))


def _fingerprints(width: int):
    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            prints = [fingerprint(t.as_buffer().to_pybytes(), width) for t in batch.column(2)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(prints, pa.int64())], ["row", "doc_id", "fp"])

    return make


def fingerprints(rows: DataFrame, width: int) -> DataFrame:
    """row, doc_id, fp from columns row, doc_id (long) and text (not null)."""
    return in_arrow(rows.select("row", "doc_id", F.col("text").cast("binary")), _fingerprints(width), "row long, doc_id long, fp long")


def _turned(fp, start, bits: int):
    """The fingerprint with the ring turned so that segment start comes first."""
    by = (start * bits).cast("int")
    return F.when(by == 0, fp).otherwise(F.call_function("shiftleft", fp, by).bitwiseOR(F.call_function("shiftrightunsigned", fp, F.lit(64) - by)))


def _top(fp, n: int):
    return fp if n == 64 else F.shiftrightunsigned(fp, 64 - n)


def links(prints: DataFrame, max_bits: int = 2, segments: int = SEGMENTS, crowd: int = CROWD) -> DataFrame:
    """Rows (a, b) that connect all distinct values of column fp within max_bits of each other."""
    bits = 64 // segments
    zero = (segments - 1) // max_bits  # chains of so many segments have a budget of zero
    keyed = prints.select("fp", F.explode(F.array(*[F.lit(k) for k in range(segments)])).alias("start")).withColumn("turned", _turned(F.col("fp"), F.col("start"), bits))
    keyed = keyed.select("start", _top(F.col("turned"), zero * bits).alias("key"), "turned", "fp")
    met = keyed.groupBy("start", "key").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    keyed = shuffled(keyed).join(met, ["start", "key"])
    few = keyed if max_bits != 2 else keyed.where(F.col("n") <= crowd)
    x, y = few.select("start", "key", F.col("turned").alias("x"), F.col("fp").alias("a")), few.select("start", "key", F.col("turned").alias("y"), F.col("fp").alias("b"))
    differ = F.col("x").bitwiseXOR(F.col("y"))
    chain = F.lit(True)
    for n in range(zero + 1, segments + 1):
        if n * max_bits // segments != (n + 1) * max_bits // segments or n == segments:  # the longest prefix of each budget implies the shorter ones of that budget
            chain = chain & (F.bit_count(_top(differ, n * bits)) <= n * max_bits // segments)
    pairs = shuffled(x).join(y, ["start", "key"]).where(F.col("a") < F.col("b")).where(chain).select("a", "b")
    if max_bits != 2:
        return pairs.distinct()
    many = keyed.where(F.col("n") > crowd).select("fp").distinct()
    middle = F.explode(F.concat(F.array("fp"), F.transform(F.sequence(F.lit(0), F.lit(63)), lambda k: F.col("fp").bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("long"), k.cast("int"))))))
    spread = many.select("fp", middle.alias("middle"))
    hubs = spread.groupBy("middle").agg(F.min("fp").alias("hub"), F.count(F.lit(1)).alias("n")).where("n > 1")
    stars = shuffled(spread).join(hubs, "middle").where("fp <> hub").select(F.col("hub").alias("a"), F.col("fp").alias("b"))
    return pairs.union(stars).distinct()


def grouped(table: DataFrame, max_bits: int = 2, segments: int = SEGMENTS) -> DataFrame:
    """From a staged table (row, doc_id, fp): fp, low_id, low_row, size of each component of two rows or more."""
    nodes = staged(table.groupBy("fp").agg(F.min(F.struct(F.coalesce("doc_id", F.lit(2**63 - 1)).alias("i"), F.col("row").alias("r"))).alias("low"), F.count(F.lit(1)).alias("n")), "nodes")
    roots = components(links(nodes.select("fp"), max_bits, segments)).withColumnRenamed("node", "fp")
    named = nodes.join(roots, "fp", "left").select("fp", "low", "n", F.coalesce("root", "fp").alias("root"))
    named = staged(named, "named")
    low = named.groupBy("root").agg(F.min("low").alias("low"), F.sum("n").alias("size")).where("size > 1")
    return named.select("fp", "root").join(low, "root").select("fp", F.when(F.col("low.i") != 2**63 - 1, F.col("low.i")).alias("low_id"), F.col("low.r").alias("low_row"), "size")


def simhash_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 3, max_bits: int = 2, segments: int = SEGMENTS) -> DataFrame:
    """One row per input row: doc_id, fingerprint (16 hex digits), component_id, group_size.

    component_id is the smallest id that can be reached over links of at most
    max_bits differing bits, the row's own id included; rows without words have
    fingerprint zero and link like any other. Null ids never name a component;
    a component of null ids only has none.
    """
    rows = text_table(docs, id_col, text_col).withColumn("row", F.monotonically_increasing_id())
    table = staged(fingerprints(rows, width), "prints")
    joined = table.select("doc_id", "fp").join(grouped(table, max_bits, segments), "fp", "left")
    return joined.select(
        "doc_id",
        F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"),
        F.when(F.col("size").isNull(), F.col("doc_id")).otherwise(F.col("low_id")).alias("component_id"),
        F.coalesce("size", F.lit(1).cast("long")).alias("group_size"),
    )


#: Segments of the wide ring, and the share of them that may differ: two texts of similarity 0.8 differ in a fifth on average.
RING, RING_DIFFER = 32, 10
SIMILAR = 0.8
#: Sets of fewer shingles are met by an exact prefix of their hashes: on rings of theirs one changed shingle fills many segments.
SHORT = 64


def shingle_hashes(text: bytes, width: int, seed: int = 42) -> np.ndarray:
    """Distinct hashes of the word shingles, sorted; a text of fewer words is one shingle, one without words has none."""
    words = text.translate(LOWER).split()
    if not words:
        return np.zeros(0, np.uint64)
    n = max(1, len(words) - width + 1)
    digest = xxhash.xxh64_intdigest
    return np.unique(np.array([digest(b" ".join(words[i : i + width]), seed) for i in range(n)], np.uint64))


def ring_of(hashes: np.ndarray) -> np.ndarray:
    """RING segments: each the SimHash of the one shingle with the smallest hash of its share of the hash space; an empty share takes the next one's."""
    if not len(hashes):
        return np.zeros(RING, np.uint64)
    starts = np.searchsorted(hashes, np.arange(RING, dtype=np.uint64) * np.uint64((1 << 64) // RING))
    ends = np.append(starts[1:], len(hashes))
    out = np.where(starts < ends, hashes[np.minimum(starts, len(hashes) - 1)], np.uint64(0))
    full = np.flatnonzero(starts < ends)
    empty = np.flatnonzero(starts >= ends)
    if len(empty):
        out[empty] = out[full[np.searchsorted(full, empty) % len(full)]]
    return out


def _chain_keys(length: int):
    """A key for each run of so many segments of column ring, its start included."""
    parts = lambda i: [F.get("ring", (i + k) % RING) for k in range(length)]
    return F.transform(F.sequence(F.lit(0), F.lit(RING - 1)), lambda i: F.xxhash64(F.lit(length), i, *parts(i)))


def prefix_of(hashes: np.ndarray, similarity: float) -> np.ndarray:
    """The smallest hashes, so many that two sets of the similarity share one of them; zero stands for a set of none."""
    n = len(hashes)
    return hashes[: n - math.ceil(similarity * n - 1e-9) + 1] if n else np.zeros(1, np.uint64)


def _rings(width: int, similarity: float):
    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rings, sizes, firsts, prints = [], [], [], []
            for t in batch.column(2):
                hashes = shingle_hashes(t.as_buffer().to_pybytes(), width)
                n = len(hashes)
                rings.append(ring_of(hashes).astype(np.uint32).view(np.int32) if n >= SHORT else None)  # the low half: the high bits name the share
                sizes.append(n)
                firsts.append(prefix_of(hashes, similarity).view(np.int64) if similarity * n < SHORT else None)
                prints.append(_bits(hashes) if n else 0)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(sizes, pa.int32()), pa.array(rings, pa.list_(pa.int32())), pa.array(firsts, pa.list_(pa.int64())), pa.array(prints, pa.int64())], ["row", "doc_id", "n", "ring", "first", "fp"])

    return make


def _sets(width: int):
    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = [shingle_hashes(t.as_buffer().to_pybytes(), width).view(np.int64) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sets, pa.list_(pa.int64()))], ["row", "hashes"])

    return make


#: Most rows and shingle hashes of a block of a crowd: what one task compares is two blocks.
BLOCK_ROWS, BLOCK_HASHES = 2048, 1 << 18


def _met_in_blocks(similarity: float):
    """Links between the rows of two blocks (or within one) whose sets have the similarity, as few as connect what they connect beyond the roots given."""

    def compare(cell: pa.Table) -> pa.Table:
        rows, roots, salts = cell["row"].to_pylist(), cell["root"].to_pylist(), cell["salt"].to_numpy()
        sets = [np.array(h, np.int64) for h in cell["hashes"].to_pylist()]
        parent = {r: r for r in roots}

        def root(x: int) -> int:
            while parent[x] != x:
                parent[x] = parent[parent[x]]
                x = parent[x]
            return x

        left, right = np.flatnonzero(salts == cell["lo"][0].as_py()), np.flatnonzero(salts == cell["hi"][0].as_py())
        sizes = np.array([len(sets[i]) for i in left], np.int64)
        hashes, owners = np.concatenate([np.zeros(0, np.int64), *[sets[i] for i in left]]), np.repeat(np.arange(len(left)), sizes)
        order = np.argsort(hashes, kind="stable")
        hashes, owners = hashes[order], owners[order]
        apart, out = len(parent), []
        for j in right.tolist():
            if apart == 1:
                break
            first = np.searchsorted(hashes, sets[j], "left")
            many = np.searchsorted(hashes, sets[j], "right") - first
            common = np.bincount(owners[np.arange(many.sum()) + np.repeat(first - np.cumsum(many) + many, many)], minlength=len(left))
            for i in left[common >= similarity * (sizes + len(sets[j]) - common)].tolist():
                x, y = root(roots[i]), root(roots[j])
                if x != y:
                    parent[max(x, y)] = min(x, y)
                    apart -= 1
                    out.append((rows[i], rows[j]))
        return pa.table({"a": pa.array([p[0] for p in out], pa.int64()), "b": pa.array([p[1] for p in out], pa.int64())})

    return compare


def crowd_links(many: DataFrame, found: DataFrame, sets: DataFrame, similarity: float) -> DataFrame | None:
    """Links (a, b) that connect the rows of crowded keys (key, row) exactly, beyond the links found so far; None if those connect each key already.

    Rows that share a key, or a chain of keys, whose members are not yet connected are one crowd. A crowd is
    dealt to blocks of bounded size by a hash of the row; each two blocks are compared whole in one task.
    """
    named = components(found)
    rooted = shuffled(many).join(named, many["row"] == named["node"], "left").select("key", "row", F.coalesce("root", "row").alias("root"))
    open_keys = rooted.groupBy("key").agg(F.min("root").alias("low"), F.max("root").alias("high")).where("low <> high").select("key", "low")
    rooted = staged(shuffled(rooted).join(open_keys, "key").select("low", "row", "root").distinct(), "crowded")
    if rooted.isEmpty():
        return None
    crowds = components(rooted.select("low", "root").distinct())
    rows = shuffled(rooted.select("row", "root").distinct()).join(crowds.withColumnsRenamed({"node": "n0", "root": "crowd"}), F.col("root") == F.col("n0"), "left")
    rows = staged(shuffled(rows.select("row", "root", F.coalesce("crowd", "root").alias("crowd"))).join(sets.select("row", F.size("hashes").alias("n")), "row"), "crowds")
    blocks = rows.groupBy("crowd").agg(F.greatest(F.ceil(F.count(F.lit(1)) / BLOCK_ROWS), F.ceil(F.sum("n") / BLOCK_HASHES), F.lit(1)).alias("blocks"))
    dealt = rows.join(blocks, "crowd").withColumn("salt", F.pmod(F.xxhash64("row"), "blocks")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = shuffled(dealt.select("crowd", F.least("salt", "other").alias("lo"), F.greatest("salt", "other").alias("hi"), "salt", "row", "root")).join(sets, "row")
    workers_see_package(many.sparkSession)
    return dealt.groupBy("crowd", "lo", "hi").applyInArrow(_met_in_blocks(similarity), "a long, b long")


def print_links(table: DataFrame, max_bits: int = 2) -> DataFrame:
    """Links (a < b) of row numbers that connect rows (row, fp) whose SimHash fingerprints differ in at most max_bits bits, met as in links: each row and the smallest of its fingerprint, and the smallest ones of linked fingerprints."""
    nodes = staged(table.groupBy("fp").agg(F.min("row").alias("low")), "prints")
    same = shuffled(table).join(nodes, "fp").where("row <> low").select("low", "row")
    met = links(nodes.select("fp"), max_bits)
    side = lambda x: nodes.select(F.col("fp").alias(x), F.col("low").alias(f"low_{x}"))
    apart = met.join(shuffled(side("a")), "a").join(shuffled(side("b")), "b").select(F.least("low_a", "low_b"), F.greatest("low_a", "low_b"))
    return same.union(apart).toDF("a", "b")


def similar_links(rows: DataFrame, width: int = 5, similarity: float = SIMILAR, crowd: int = CROWD) -> tuple[DataFrame, DataFrame]:
    """The staged rings of numbered rows (row, doc_id, text), and links (a, b) of row numbers whose shingle sets have at least the similarity.

    Candidates are rows whose SimHash fingerprints, of the same shingles, are linked by pigeonring chains (see print_links), and,
    since fingerprints of similarity 0.8 are mostly further apart, these: of sets of SHORT shingles or more, candidates share a chain of three equal segments, the longest that a
    budget of RING_DIFFER in RING leaves without difference. A pair with a shorter set shares one of the smallest
    hashes of both (see prefix_of), which misses none. Sizes must allow the similarity; the Jaccard
    similarity of the whole shingle sets then decides alone. In a key that
    more than crowd rows share each row first meets the key's smallest row; keys that these links leave
    in parts have all their rows compared, see crowd_links.
    """
    table = staged(in_arrow(rows.select("row", "doc_id", F.col("text").cast("binary")), _rings(width, similarity), "row long, doc_id long, n int, ring array<int>, first array<long>, fp long"), "rings")
    chains = F.when(F.col("ring").isNotNull(), _chain_keys(3))
    firsts = F.transform("first", lambda h: F.xxhash64(F.lit(0), h))
    none = F.array().cast("array<long>")
    keyed = table.select("row", F.explode(F.concat(F.coalesce(chains, none), F.coalesce(firsts, none))).alias("key"))
    met = staged(keyed.groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.min("row").alias("hub")).where("n > 1"), "met")
    members = shuffled(keyed).join(met, "key")
    few = members.where(F.col("n") <= crowd).select("key", "row")
    pairs = shuffled(few.select("key", F.col("row").alias("a"))).join(few.select("key", F.col("row").alias("b")), "key").where("a < b").select("a", "b")
    many = staged(members.where(F.col("n") > crowd).select("key", "row", "hub"), "many")
    stars = many.where("row <> hub").select(F.col("hub").alias("a"), F.col("row").alias("b"))
    crowded = many.select("row").distinct()
    pairs = pairs.union(stars).union(print_links(table.select("row", "fp"))).distinct()
    side = lambda x: table.select(F.col("row").alias(x), F.col("n").alias(f"n{x}"))
    near = staged(pairs.join(shuffled(side("a")), "a").join(shuffled(side("b")), "b").where(F.least("na", "nb") >= similarity * F.greatest("na", "nb")).select("a", "b"), "near")
    wanted = near.select(F.explode(F.array("a", "b")).alias("row")).union(crowded)
    sets = staged(in_arrow(marked(rows, wanted).where("marked").select("row", F.col("text").cast("binary")), _sets(width), "row long, hashes array<long>"), "sets")
    both = near.join(shuffled(sets.select(F.col("row").alias("a"), F.col("hashes").alias("ha"))), "a").join(shuffled(sets.select(F.col("row").alias("b"), F.col("hashes").alias("hb"))), "b")
    common = F.size(F.array_intersect("ha", "hb"))
    found = staged(both.where(common >= similarity * (F.size("ha") + F.size("hb") - common)).select("a", "b"), "found")
    more = None if many.isEmpty() else crowd_links(many.select("key", "row"), found, sets, similarity)
    return table, found if more is None else found.union(more)


def drop_near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5, similarity: float = SIMILAR, stable: bool = False) -> DataFrame:
    """docs with one row of each near-duplicate group, the one with the smallest id (null ids last); all columns stay.

    A group is connected by links of at least the similarity over sets of five-word shingles. Rows
    without words are copies of each other. See similar_links for how candidates are met, and
    the README for the measured recall. For stable see numbered.
    """
    names = docs.columns
    rows = numbered(docs, stable)
    ids, text = f"c{names.index(id_col)}", f"c{names.index(text_col)}"
    table, found = similar_links(rows.select("row", F.col(ids).cast("long").alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text")), width, similarity)
    named = components(found)
    named = named.union(named.select("root", "root").distinct()).toDF("row", "root").join(shuffled(table.select("row", "doc_id")), "row")
    named = staged(named, "named")
    low = named.groupBy("root").agg(F.min(F.struct(F.coalesce("doc_id", F.lit(2**63 - 1)).alias("i"), "row")).alias("low"))
    gone = shuffled(named).join(low, "root").where("row <> low.row").select("row")
    return without(rows, gone, names)
