"""Token ids in files of patched frame-of-reference blocks.

A segment is a file image: magic, counts, document ids and lengths, the start
of every block, then the blocks. A block of up to BLOCK ids stores its minimum, the bit
width that holds PERCENTILE of the differences to it, the differences' low bits
packed at that width, and an exception list (position, whole difference) for the rest. Segments lie
in a table in the shared folder, one row each, so that any store that Spark
reaches can hold them; export_segments writes plain files.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tmotif.llm.common import NO_ID, in_arrow, staged, text_table
from tmotif.llm.tokens import encoder, merges_by_name

MAGIC = b"PFR2"
BLOCK = 1024
PERCENTILE = 0.95
#: A segment ends with the document that brings it to so many ids.
SEGMENT = 1 << 19
END = 2


def _widths(rest: np.ndarray) -> np.ndarray:
    """Bits that hold the percentile of each row."""
    k = min(rest.shape[1] - 1, int(np.ceil(PERCENTILE * rest.shape[1])) - 1)
    top = np.partition(rest, k, axis=1)[:, k].astype(np.uint64)
    return np.frexp(top.astype(np.float64))[1].astype(np.int64)


def _packed(rest: np.ndarray, width: int) -> np.ndarray:
    """Low bits of every value, one row of bytes per block: eight values are width bytes."""
    if not width:
        return np.zeros((len(rest), 0), np.uint8)
    if width in (8, 16, 32):
        return np.ascontiguousarray(rest.astype(f"<u{width // 8}")).view(np.uint8).reshape(len(rest), -1)
    size = -(-rest.shape[1] // 8)
    low = np.zeros((len(rest), 8 * size), np.uint64)
    low[:, : rest.shape[1]] = rest & np.uint32((1 << width) - 1)
    out = np.zeros((len(rest), size, width), np.uint8)
    for j in range(8):
        byte, bit = divmod(j * width, 8)
        value = low[:, j::8] << np.uint64(bit)
        for b in range(-(-(bit + width) // 8)):
            out[:, :, byte + b] |= (value >> np.uint64(8 * b)).astype(np.uint8)
    return out.reshape(len(rest), -1)[:, : -(-rest.shape[1] * width // 8)]


def _unpacked(raw: np.ndarray, width: int, n: int) -> np.ndarray:
    if not width:
        return np.zeros((len(raw), n), np.uint32)
    if width in (8, 16, 32):
        return np.ascontiguousarray(raw).view(f"<u{width // 8}").astype(np.uint32)
    size = -(-n // 8)
    eights = np.zeros((len(raw), size * width), np.uint8)
    eights[:, : raw.shape[1]] = raw
    eights = eights.reshape(len(raw), size, width)
    out = np.zeros((len(raw), size, 8), np.uint32)
    for j in range(8):
        byte, bit = divmod(j * width, 8)
        value = np.zeros((len(raw), size), np.uint64)
        for b in range(-(-(bit + width) // 8)):
            value |= eights[:, :, byte + b].astype(np.uint64) << np.uint64(8 * b)
        out[:, :, j] = (value >> np.uint64(bit)) & np.uint64((1 << width) - 1)
    return out.reshape(len(raw), -1)[:, :n]


def encode_blocks(ids: np.ndarray) -> tuple[np.ndarray, bytes]:
    """Byte start of each block, and the blocks."""
    full = len(ids) // BLOCK * BLOCK
    blocks: list[bytes] = []
    for part in (ids[:full].reshape(-1, BLOCK), ids[full:].reshape(-1, max(1, len(ids) - full))):
        made: list[bytes] = [b""] * len(part)
        for k in range(0, len(part), 256):
            some = part[k : k + 256].astype(np.uint32)
            least = some.min(axis=1)
            rest = some - least[:, None]
            widths = _widths(rest)
            for w in np.unique(widths):
                at = np.flatnonzero(widths == w)
                over = rest[at] >> np.uint32(w) != 0 if w < 32 else np.zeros((len(at), rest.shape[1]), bool)
                raw = _packed(rest[at], int(w))
                for j, b in enumerate(at):
                    where = np.flatnonzero(over[j])
                    made[k + b] = struct.pack("<IBHH", int(least[b]), int(w), rest.shape[1], len(where)) + raw[j].tobytes() + where.astype("<u2").tobytes() + rest[b][where].astype("<u4").tobytes()
        blocks += made
    return np.cumsum([0, *map(len, blocks)])[:-1].astype("<u8"), b"".join(blocks)


def decode_blocks(starts: np.ndarray, raw: bytes) -> np.ndarray:
    heads = [struct.unpack_from("<IBHH", raw, int(s)) for s in starts]
    out: list = [None] * len(heads)
    kinds: dict[tuple[int, int], list[int]] = {}
    for k, (_, w, n, _) in enumerate(heads):
        kinds.setdefault((w, n), []).append(k)
    for (w, n), which in kinds.items():
        size = -(-n * w // 8)
        for at in range(0, len(which), 256):
            some = which[at : at + 256]
            rows = np.frombuffer(b"".join([raw[int(starts[k]) + 9 : int(starts[k]) + 9 + size] for k in some]), np.uint8).reshape(len(some), size)
            for k, values in zip(some, _unpacked(rows, w, n), strict=True):
                base, _, _, odd = heads[k]
                if odd:
                    p = int(starts[k]) + 9 + size
                    values[np.frombuffer(raw, "<u2", odd, p)] = np.frombuffer(raw, "<u4", odd, p + 2 * odd)
                out[k] = values + np.uint32(base)
    return np.concatenate(out) if out else np.zeros(0, np.uint32)


def write_segment(doc_ids: list[int | None], lengths: list[int], ids: np.ndarray) -> bytes:
    starts, blocks = encode_blocks(ids)
    head = MAGIC + struct.pack("<QII", len(ids), len(doc_ids), len(starts))
    return head + np.array([NO_ID if d is None else d for d in doc_ids], "<i8").tobytes() + np.array(lengths, "<u4").tobytes() + starts.tobytes() + blocks


def read_segment(image: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Document ids (NO_ID: none), lengths, ids."""
    if image[:4] != MAGIC:
        raise ValueError("not a segment")
    n, docs, blocks = struct.unpack_from("<QII", image, 4)
    p = 20
    doc_ids, lengths = np.frombuffer(image, "<i8", docs, p), np.frombuffer(image, "<u4", docs, p + 8 * docs)
    starts = np.frombuffer(image, "<u8", blocks, p + 12 * docs)
    ids = decode_blocks(starts, image[p + 12 * docs + 8 * blocks :])
    if len(ids) != n:
        raise ValueError("segment is cut short")
    return doc_ids, lengths, ids


def block_of(image: bytes, number: int) -> np.ndarray:
    """Ids of one block alone, by the index of block starts."""
    _, docs, blocks = struct.unpack_from("<QII", image, 4)
    p = 20 + 12 * docs
    at = int(np.frombuffer(image, "<u8", blocks, p)[number])
    return decode_blocks(np.zeros(1, np.int64), image[p + 8 * blocks + at :])


def _segments(path: str, end: int, by_name: bool):
    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        encode, part, seq = encoder(path), TaskContext.get().partitionId(), 0
        docs, lengths, held, total = [], [], [], 0

        def flush() -> pa.RecordBatch:
            image = write_segment(docs, lengths, np.concatenate(held))
            return pa.RecordBatch.from_arrays([pa.array([part], pa.int64()), pa.array([seq], pa.int64()), pa.array([total], pa.int64()), pa.array([image], pa.binary())], ["part", "seq", "n_tokens", "image"])

        for batch in batches:
            ids, n = encode.column(batch.column(1), by_name)
            ids, n = np.insert(ids, np.cumsum(n), np.uint32(end)), n + 1
            ends, sizes, first = np.cumsum(n).tolist(), n.tolist(), 0
            for k, doc_id in enumerate(batch.column(0).to_pylist()):
                docs.append(doc_id)
                lengths.append(sizes[k])
                total += sizes[k]
                if total >= SEGMENT:
                    held.append(ids[first : ends[k]])
                    first = ends[k]
                    yield flush()
                    docs, lengths, held, total, seq = [], [], [], 0, seq + 1
            held.append(ids[first:])
        if docs:
            yield flush()

    return make


def write_token_files(docs: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text", end: int = END) -> DataFrame:
    """The written segments in ascending document order: part, seq, n_tokens, image."""
    spark = docs.sparkSession
    rows = text_table(docs, id_col, text_col).withColumn("row", F.monotonically_increasing_id())
    keys = [F.col("doc_id").asc_nulls_last(), F.col("row").asc()]
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    ordered = rows.repartitionByRange(parts, *keys).sortWithinPartitions(*keys).select("doc_id", "text")
    return staged(in_arrow(ordered, _segments(tokenizer, end, merges_by_name(tokenizer)), "part long, seq long, n_tokens long, image binary"), "segments")


def _documents(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for part, seq, image in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            doc_ids, lengths, ids = read_segment(image)
            raw, ends = ids.astype("<u4").tobytes(), np.cumsum(lengths.astype(np.int64))
            starts = ends - lengths
            crcs = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(starts.tolist(), ends.tolist(), strict=True)]
            n = len(doc_ids)
            yield pa.RecordBatch.from_arrays([pa.array([part] * n, pa.int64()), pa.array([seq] * n, pa.int64()), pa.array(doc_ids.astype(np.int64), mask=doc_ids == NO_ID), pa.array(starts), pa.array(lengths.astype(np.int64)), pa.array(crcs, pa.int64())], ["part", "seq", "doc_id", "start", "n_tokens", "ids_crc32"])


def read_token_files(segments: DataFrame) -> DataFrame:
    """One row per document from the files: doc_id, start (ids of all documents before it), n_tokens, ids_crc32."""
    read = in_arrow(segments.select("part", "seq", "image"), _documents, "part long, seq long, doc_id long, start long, n_tokens long, ids_crc32 long")
    sums = segments.groupBy("part", "seq").agg(F.sum("n_tokens").alias("n"))
    rows = [Window.unboundedPreceding, -1]
    whole = sums.groupBy("part").agg(F.sum("n").alias("n")).select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(*rows)), F.lit(0)).alias("a"))  # a row for each task
    within = sums.select("part", "seq", F.coalesce(F.sum("n").over(Window.partitionBy("part").orderBy("seq").rowsBetween(*rows)), F.lit(0)).alias("b"))
    starts = within.join(whole, "part").select("part", "seq", (F.col("a") + F.col("b")).alias("first"))
    return read.join(starts, ["part", "seq"]).select("doc_id", (F.col("start") + F.col("first")).alias("start"), "n_tokens", "ids_crc32")


def export_segments(segments: DataFrame, folder: str) -> list[str]:
    """Plain files, one per segment, in order; for a folder that the driver reaches."""
    names = []
    for row in segments.orderBy("part", "seq").toLocalIterator():
        names.append(str(Path(folder) / f"{row['part']:06d}-{row['seq']:06d}.pfr"))
        Path(names[-1]).write_bytes(row["image"])
    return names


def token_file_index(docs: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text", end: int = END) -> DataFrame:
    """Write, then read back. A null text is the end id alone; null ids come last; repeated rows are documents of their own."""
    return read_token_files(write_token_files(docs, tokenizer, id_col, text_col, end))
