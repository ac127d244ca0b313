"""Packing by the length histogram, shortest pack first.

Documents are cut at multiples of the sequence length, so that all pieces but a
document's last are full. The histogram of piece lengths (as many rows as a
sequence has tokens, at most) comes to the driver, where lengths are placed
longest first: each goes to the packs that are shortest so far, as long as it
fits, else to new packs. Equal packs are one pattern with a count, so that the
work depends on the number of lengths and patterns, not on that of documents.
A piece finds its pattern by its rank among the pieces of its length; ranks come from
counts by (task, length), so no length is gathered anywhere.
"""

from __future__ import annotations

import heapq
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tmotif.llm.common import in_arrow, staged, text_table
from tmotif.llm.tokens import encoder

LENGTH = 2048
END = 1


def pack_histogram(counts: dict[int, int], size: int = LENGTH) -> list[tuple[tuple[int, ...], int]]:
    """(lengths, longest first; how many packs) from a histogram of lengths of at most size."""
    open_packs: list[tuple[int, int, tuple[int, ...], int]] = []  # (tokens, age, lengths, count), the shortest first
    age, done = 0, []
    for length in sorted((k for k, n in counts.items() if n), reverse=True):
        left, grown = counts[length], []
        while left:
            if open_packs and open_packs[0][0] + length <= size:
                tokens, _, lengths, n = heapq.heappop(open_packs)
                fit = min(n, left)  # a pack takes one piece of a length at a time, then stands by its new size
                if n > fit:
                    age += 1
                    heapq.heappush(open_packs, (tokens, age, lengths, n - fit))
                grown = [(tokens + length, (*lengths, length), fit)]
                left -= fit
            else:
                each = 1 if not open_packs and size // length < 2 else size // length
                if left >= each:
                    grown, left = [(length * each, (length,) * each, left // each)], left % each
                else:
                    grown, left = [(length * left, (length,) * left, 1)], 0
            for tokens, lengths, n in grown:
                age += 1
                if tokens == size:
                    done.append((lengths, n))
                else:
                    heapq.heappush(open_packs, (tokens, age, lengths, n))
    return done + [(lengths, n) for _, _, lengths, n in open_packs]


def _pieces(path: str, size: int, end: int, with_ids: bool):
    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        encode, part, seen = encoder(path), TaskContext.get().partitionId(), np.zeros(size + 1, np.int64)
        last = np.array([end], "<u4").tobytes()
        for batch in batches:
            rows = []
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                raw = encode(text) + last
                n = len(raw) // 4
                for at in range(0, n, size):
                    piece = raw[4 * at : 4 * (at + size)]
                    k = len(piece) // 4
                    rows.append((doc_id, at, k, zlib.crc32(piece), n, part, int(seen[k]), piece if with_ids else None))
                    seen[k] += 1
            cols = [*zip(*rows, strict=True)] if rows else [()] * 8
            kinds = [pa.int64()] * 7 + [pa.binary()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "part", "nth", "ids"])

    return make


def _placed(lengths: np.ndarray, firsts: np.ndarray, sequences: np.ndarray, offsets: np.ndarray):
    """Slots sorted by (length, first rank): the slot of a piece is the last one at or below its (length, rank)."""
    present, first = np.unique(lengths, return_index=True)
    starts = {int(k): (int(a), int(b)) for k, a, b in zip(present, first, np.append(first[1:], len(lengths)), strict=False)}

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, rank = (batch.column(batch.schema.get_field_index(c)).to_numpy() for c in ("length", "rank"))
            sequence, offset = np.zeros(len(n), np.int64), np.zeros(len(n), np.int64)
            for k in np.unique(n):
                a, b = starts[int(k)]
                at = n == k
                slot = a + np.searchsorted(firsts[a:b], rank[at], side="right") - 1
                sequence[at], offset[at] = sequences[slot] + rank[at] - firsts[slot], offsets[slot]
            keep = [c for c in batch.schema.names if c != "rank"]
            yield pa.RecordBatch.from_arrays([*(batch.column(batch.schema.get_field_index(c)) for c in keep), pa.array(sequence), pa.array(offset)], [*keep, "sequence_id", "offset"])

    return make


def pack_documents(docs: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text", size: int = LENGTH, end: int = END, with_ids: bool = False) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset (and ids, if asked for).

    A document is its ids and then the end id; a null or empty text is the end
    id alone. Each id lies in one piece; the pieces of a sequence follow each
    other without gaps from offset 0. Repeated rows are documents of their own.
    """
    table = in_arrow(text_table(docs, id_col, text_col), _pieces(tokenizer, size, end, with_ids), "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, part long, nth long, ids binary")
    table = staged(table if with_ids else table.drop("ids"), "pieces")
    parts = table.groupBy("length", "part").agg(F.count(F.lit(1)).alias("n"))
    before = F.sum("n").over(Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1))
    ranked = table.join(parts.select("length", "part", F.coalesce(before, F.lit(0)).alias("before")), ["length", "part"]).withColumn("rank", F.col("nth") + F.col("before"))
    counts = {r["length"]: r["n"] for r in table.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}
    slots, used, sequence = [], dict.fromkeys(counts, 0), 0
    for lengths, n in pack_histogram(counts, size):
        offset = 0
        for length in lengths:
            slots.append((length, used[length], sequence, offset))
            used[length] += n
            offset += length
        sequence += n
    slots.sort()
    cols = [np.array(c, np.int64) for c in (zip(*slots, strict=True) if slots else [[]] * 4)]
    names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", *(["ids"] if with_ids else [])]
    kinds = ", ".join(f"{c} {'binary' if c == 'ids' else 'long'}" for c in names)
    return in_arrow(ranked.select(*names, "rank"), _placed(*cols), f"{kinds}, sequence_id long, offset long")


def sequences(pieces: DataFrame) -> DataFrame:
    """sequence_id, n_tokens, ids (little-endian unsigned 32-bit) from pieces with ids."""
    rows = pieces.groupBy("sequence_id").agg(F.sum("length").alias("n_tokens"), F.array_sort(F.collect_list(F.struct("offset", "ids"))).alias("p"))
    return rows.select("sequence_id", "n_tokens", F.aggregate("p", F.lit(b""), lambda acc, x: F.concat(acc, x["ids"])).alias("ids"))


def padding(pieces: DataFrame, size: int = LENGTH) -> DataFrame:
    """One row: sequences, tokens, padding tokens and their share; lengths that are a power of two need none."""
    each = pieces.groupBy("sequence_id").agg(F.sum("length").alias("n"))
    pad = F.when(F.bit_count("n") == 1, 0).otherwise(size - F.col("n"))
    return each.agg(F.count(F.lit(1)).alias("sequences"), F.sum("n").alias("tokens"), F.sum(pad).alias("padding"), (F.sum(pad) / (F.sum(pad) + F.sum("n"))).alias("padding_share"))
