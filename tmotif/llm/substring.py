"""Substring dedup by sliding sentence spans.

A text is parted into sentences that together are the whole text; to keep them short and to find the same
ones wherever a passage begins, the parts are chosen by their surroundings alone: of every REACH
consecutive words the one that begins a sentence, or else the one with the smallest hash, begins a part.
Of a passage that two documents share, all parts are then the same but for less than REACH words at each end.

From each part on, the run of consecutive parts that first reaches LEAST_WORDS words is hashed, and
hashes are joined over all documents. Of a run that occurs more than once all but the first (by document,
then place) are marked, and the parts under a mark are removed. A passage of 3 * REACH + LEAST_WORDS - 1 words (51)
or more holds at least one whole run, so none is missed.

A document sends each of its runs once; counting combines before the shuffle, so that a run that a
third of all rows share is one row per task. Later places in the same document need no join.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import xxhash

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tmotif.llm.common import NO_ID, in_arrow

#: Of so many consecutive words at least one begins a part.
REACH = 10
#: Words of a run: shorter repeats (set phrases, licence lines) are no copies.
LEAST_WORDS = 22
WORD = re.compile(rb"[^\x20\x09-\x0D]+")
#: The marks that end a sentence, if they end a word; a line feed ends one, too.
MARKS = b".!?"
LATE = np.uint64(1 << 63)
PLACE = np.uint64((1 << 32) - 1)


def words_of(text: bytes) -> tuple[list[bytes], np.ndarray]:
    """The words, and which of them begin a sentence."""
    lines = [x.split() for x in text.split(b"\n")]  # bytes.split() parts at the six ASCII white space characters
    words = list(chain.from_iterable(lines))
    begins = np.zeros(len(words) + 1, bool)
    begins[0] = True
    begins[np.cumsum([len(x) for x in lines])] = True
    begins[1:] |= np.fromiter((w[-1] in MARKS for w in words), bool, len(words))
    return words, begins[:-1]


def part_starts(words: list[bytes], begins: np.ndarray, reach: int = REACH) -> np.ndarray:
    """Numbers of the words that begin a part, and the number of words."""
    n = len(words)
    cut = np.zeros(n + 1, bool)
    cut[0] = cut[n] = True
    if n >= reach:
        hashes = np.fromiter(map(xxhash.xxh32_intdigest, words), np.uint64, n) >> np.uint64(1)
        low = hashes << np.uint64(32) | PLACE - np.arange(n, dtype=np.uint64)  # of equal words the last one
        low[~begins] |= LATE
        done = 1
        while done < reach:
            by = min(done, reach - done)
            low, done = np.minimum(low[:-by], low[by:]), done + by
        cut[(PLACE - (low & PLACE)).astype(np.int64)] = True
    return np.flatnonzero(cut)


def runs_of(text: bytes, reach: int = REACH, least: int = LEAST_WORDS) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Parts' first words (and the number of words), each run's end (a part number; run k begins at part k), and 128-bit hashes as two numbers a run."""
    words, begins = words_of(text)
    starts = part_starts(words, begins, reach) if words else np.zeros(1, np.int64)
    ends = np.searchsorted(starts, starts + least)
    ends = ends[ends < len(starts)]
    at = np.zeros(len(words) + 1, np.int64)
    np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1, out=at[1:])
    line, digest = b" ".join(words), xxhash.xxh3_128_digest
    hashes = b"".join([digest(line[a:b]) for a, b in zip(at[starts[: len(ends)]].tolist(), (at[starts[ends]] - 1).tolist(), strict=True)])
    return starts, ends, np.frombuffer(hashes, "<i8").reshape(-1, 2)


def _runs(reach: int, least: int):
    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found, sizes = [np.zeros((0, 2), np.int64)], []
            for t in batch.column(1):
                hashes = runs_of(t.as_buffer().to_pybytes(), reach, least)[2]
                found.append(hashes[np.unique(hashes[:, 0], return_index=True)[1]])
                sizes.append(len(found[-1]))
            rows = np.concatenate(found)
            key = np.repeat(batch.column(0).to_numpy(), sizes)
            yield pa.RecordBatch.from_arrays([pa.array(rows[:, 0]), pa.array(rows[:, 1].astype(np.int32)), pa.array(key)], ["h", "g", "d"])

    return make


def repeated_runs(rows: DataFrame, reach: int = REACH, least: int = LEAST_WORDS) -> DataFrame:
    """d, marks (hashes of its runs that an earlier document has) from rows (d, text as binary). Hashes of 96 bits decide."""
    found = in_arrow(rows, _runs(reach, least), "h long, g int, d long")
    first = found.groupBy("h", "g").agg(F.min("d").alias("low"), F.max("d").alias("high")).where("low <> high").select("h", "g", "low")
    return found.join(first, ["h", "g"]).where("d <> low").groupBy("d").agg(F.collect_set("h").alias("marks"))


def covered_parts(starts: np.ndarray, ends: np.ndarray, hashes: np.ndarray, marks: np.ndarray) -> np.ndarray:
    """Numbers of the parts under a marked run, or under one that occurs earlier in the document."""
    again = np.ones(len(ends), bool)
    again[np.unique(hashes[:, 0], return_index=True)[1]] = False
    runs = np.flatnonzero(again | np.isin(hashes[:, 0], marks))
    change = np.zeros(len(starts), np.int64)
    np.add.at(change, runs, 1)
    np.add.at(change, ends[runs], -1)
    return np.flatnonzero(np.cumsum(change) > 0)


def left_over(text: bytes, starts: np.ndarray, gone: np.ndarray) -> bytes:
    """The text without the parts gone. A part begins with its first word, the first one with the text."""
    at = [m.start() for m in WORD.finditer(text)]
    edges = [0, *(at[k] for k in starts[1:-1].tolist()), len(text)]
    dropped = set(gone.tolist())
    return b"".join([text[a:b] for k, (a, b) in enumerate(zip(edges, edges[1:], strict=False)) if k not in dropped])


def _cut(reach: int, least: int):
    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes, removed, texts = [], [], []
            for t, marks in zip(batch.column(1), batch.column(2), strict=True):
                text = t.as_buffer().to_pybytes()
                starts, ends, hashes = runs_of(text, reach, least)
                gone = covered_parts(starts, ends, hashes, np.array(marks.as_py() or [], np.int64))
                sizes.append(len(starts) - 1)
                removed.append(gone.astype(np.int32))
                texts.append(left_over(text, starts, gone) if len(gone) else text)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sizes, pa.int64()), pa.array(removed, pa.list_(pa.int32())), pa.array(texts, pa.binary()).cast(pa.string())], ["doc_id", "n_parts", "removed", "text"])

    return make


def _key(id_: Column, text: Column) -> Column:
    """What a document is known by: its id; without one a number of its text, beyond all ids."""
    return F.coalesce(id_.cast("long"), F.lit(NO_ID) - F.pmod(F.xxhash64(text), F.lit(1 << 31)))


def remove_repeated_spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", reach: int = REACH, least_words: int = LEAST_WORDS) -> DataFrame:
    """One row per input row: doc_id, n_parts, removed (numbers of the parts taken out, from 0), text (what is left).

    Null counts as empty and stays empty. Rows without an id come after all others. Rows with the same id, or
    with none and the same text, are one document: they don't remove each other's text. A text of
    fewer than least_words words has no run and stays whole. Other columns are not looked at.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), _key(F.col(id_col), text).alias("d"), text.cast("binary").alias("text"))
    marks = repeated_runs(rows.select("d", "text"), reach, least_words)
    joined = rows.join(marks, "d", "left").select("doc_id", "text", "marks")
    return in_arrow(joined, _cut(reach, least_words), "doc_id long, n_parts long, removed array<int>, text string")
