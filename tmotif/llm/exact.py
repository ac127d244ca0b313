"""Exact dedup by a tree-merge of sorted digest runs.

Every task of the digest table turns its rows into sorted runs, one for each
slice of the digest space: an entry for each digest with the count and the
smallest (id, row) seen. Runs then meet in binomial rounds: in round r the nodes
whose numbers agree above bit r * FAN_BITS hand their runs of a slice to the
lowest of them, which merges them and keeps the smallest identifier of equal
digests. An entry is equal only if the SHA-256, a second hash and the length
agree, so that each merge verifies what it joins. A merged run is cut into as many finer slices as runs met, so that
runs stay of one size (SLICE_ROWS rows on average) and of one number in every round, however many rows and tasks there
are; no task ever holds a whole table, and a group of copies is one entry in every run from the first round on.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tmotif.llm.common import NO_ID, SPACE_CLASS, in_arrow, numbered, shuffled, staged, text_table, without, workers_see_package

#: Rows of a run on average.
SLICE_ROWS = 50_000
#: Sixteen runs meet in a round.
FAN_BITS = 4
RUN = np.dtype([("d0", "<u8"), ("d1", "<u8"), ("d2", "<u8"), ("d3", "<u8"), ("check", "<i8"), ("size", "<i8"), ("id", "<i8"), ("row", "<i8"), ("n", "<i8")])
KEY = ["d0", "d1", "d2", "d3", "check", "size"]


def merged(runs: list[np.ndarray]) -> np.ndarray:
    """One sorted run from several: equal entries become one with the smallest (id, row) and the sum of counts.

    Runs are sorted by their first 64 digest bits, so that the stable sort of these merges
    whole runs; only entries that agree in them, copies nearly always, are then put in order among themselves.
    """
    run = np.concatenate(runs) if runs else np.zeros(0, RUN)
    run = run[np.argsort(run["d0"], kind="stable")]
    if not len(run):
        return run
    alike = run["d0"][1:] == run["d0"][:-1]
    tied = np.flatnonzero(np.append(False, alike) | np.append(alike, False))
    some = run[tied]
    run[tied] = some[np.lexsort([some[x] for x in ("row", "id", *reversed(KEY))])]
    new = np.ones(len(run), bool)
    new[1:] = np.any([run[k][1:] != run[k][:-1] for k in KEY], axis=0)
    first = np.flatnonzero(new)
    out = run[first].copy()
    out["n"] = np.add.reduceat(run["n"], first)
    return out


def in_slices(run: np.ndarray, slices: int) -> list[tuple[int, np.ndarray]]:
    """A sorted run cut at equal shares of the digest space: (share, entries) of those that have any."""
    which = (run["d0"] >> np.uint64(32)) * np.uint64(slices) >> np.uint64(32)
    cuts = np.flatnonzero(which[1:] != which[:-1]) + 1
    return [(int(which[a]), run[a:b]) for a, b in zip([0, *cuts], [*cuts, len(run)], strict=True)] if len(run) else []


def _runs(slices: int):
    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[np.ndarray]] = {}
        for batch in batches:
            cols = dict(zip(batch.schema.names, batch.columns, strict=True))
            run = np.zeros(batch.num_rows, RUN)
            raw = np.frombuffer(b"".join(cols["sha"].to_pylist()), ">u8").reshape(-1, 4)
            for k in range(4):
                run[f"d{k}"] = raw[:, k]
            run["check"], run["size"] = cols["check"].to_numpy(zero_copy_only=False), cols["size"].to_numpy(zero_copy_only=False)
            run["id"] = cols["doc_id"].fill_null(int(NO_ID)).to_numpy(zero_copy_only=False)
            run["row"], run["n"] = cols["row"].to_numpy(zero_copy_only=False), 1
            for s, part in in_slices(merged([run]), slices):
                held.setdefault(s, []).append(part)
                if len(held[s]) >= 16:
                    held[s] = [merged(held[s])]
        from pyspark import TaskContext

        node = TaskContext.get().partitionId()
        for s, runs in held.items():
            yield pa.RecordBatch.from_arrays([pa.array([s], pa.int64()), pa.array([node], pa.int64()), pa.array([merged(runs).tobytes()], pa.binary())], ["slice", "node", "run"])

    return make


def _merge(slices: int):
    """Merges the runs of a node and a slice, and cuts the result into the slices of the next round."""

    def merge(met: pa.Table) -> pa.Table:
        parts = in_slices(merged([np.frombuffer(x, RUN) for x in met["run"].to_pylist()]), slices)
        up = met["up"][0].as_py()
        return pa.table({"slice": pa.array([s for s, _ in parts], pa.int64()), "node": pa.array([up] * len(parts), pa.int64()), "run": pa.array([x.tobytes() for _, x in parts], pa.binary())})

    return merge


def _entries(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for raw in batch.column(0).to_pylist():
            run = np.frombuffer(raw, RUN)
            run = run[run["n"] > 1]
            sha = np.stack([run[f"d{k}"] for k in range(4)], axis=1).astype(">u8").tobytes()
            ids = run["id"].astype("<i8")
            yield pa.RecordBatch.from_arrays([pa.array([sha[32 * k : 32 * k + 32] for k in range(len(run))], pa.binary()), pa.array(run["check"].astype("<i8")), pa.array(run["size"].astype("<i8")), pa.array(ids, mask=ids == NO_ID), pa.array(run["row"].astype("<i8")), pa.array(run["n"].astype("<i8"))], ["sha", "check", "size", "keep_id", "keep_row", "group_size"])


def digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, row (unique, stable once staged), sha, check, size: of the text with white space runs as one space."""
    plain = text_table(docs, id_col, text_col).select("doc_id", F.regexp_replace("text", SPACE_CLASS, " ").alias("plain"))
    return plain.select("doc_id", F.monotonically_increasing_id().alias("row"), F.unhex(F.sha2("plain", 256)).alias("sha"), F.xxhash64("plain").alias("check"), F.octet_length("plain").cast("long").alias("size"))


def tree_merge(table: DataFrame) -> DataFrame:
    """Digests held by two rows or more: sha, check, size, keep_id, keep_row, group_size."""
    spark = table.sparkSession
    nodes = table.rdd.getNumPartitions()
    slices = max(1, -(-table.count() // (SLICE_ROWS * max(1, nodes))))
    runs = in_arrow(table.select("doc_id", "row", "sha", "check", "size"), _runs(slices), "slice long, node long, run binary")
    workers_see_package(spark)
    rounds = 0
    while (1 << FAN_BITS * rounds) < nodes:
        rounds += 1
        slices <<= FAN_BITS
        if slices >= 1 << 32:
            raise ValueError("more runs than the digest space has slices")
        runs = runs.withColumn("up", F.shiftright("node", FAN_BITS)).groupBy("slice", "up").applyInArrow(_merge(slices), "slice long, node long, run binary")
    return in_arrow(runs.select("run"), _entries, "sha binary, check long, size long, keep_id long, keep_row long, group_size long")


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: doc_id, keep_id, group_size, kept, text_sha256.

    Texts are equal when identical after each run of white space has become one
    space; null counts as empty. Of equal texts the row with the smallest id
    stays; of repeated rows with that id exactly one. A null id stays only where
    its whole group has none, and keep_id is null then.
    """
    table = staged(digests(docs, id_col, text_col), "digests")
    groups = tree_merge(table)
    joined = table.alias("t").join(groups.alias("g"), ["sha", "check", "size"], "left")
    single = F.col("group_size").isNull()
    return joined.select(
        "doc_id",
        F.when(single, F.col("doc_id")).otherwise(F.col("keep_id")).alias("keep_id"),
        F.coalesce("group_size", F.lit(1).cast("long")).alias("group_size"),
        (single | (F.col("row") == F.col("keep_row"))).alias("kept"),
        F.lower(F.hex("sha")).alias("text_sha256"),
    )


def drop_exact_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", stable: bool = False) -> DataFrame:
    """The rows of docs that exact_dedup keeps, with all their columns.

    Rows are dropped by number, so repeated ids and rows are told apart; for stable see numbered.
    """
    names = docs.columns
    rows = numbered(docs, stable)
    own = f"c{names.index(id_col)}", f"c{names.index(text_col)}"
    plain = rows.select(F.col(own[0]).cast("long").alias("doc_id"), "row", F.regexp_replace(F.coalesce(F.col(own[1]), F.lit("")), SPACE_CLASS, " ").alias("plain"))
    table = staged(plain.select("doc_id", "row", F.unhex(F.sha2("plain", 256)).alias("sha"), F.xxhash64("plain").alias("check"), F.octet_length("plain").cast("long").alias("size")), "digests")
    return without(rows, shuffled(table).join(tree_merge(table), ["sha", "check", "size"]).where("row <> keep_row").select("row"), names)
