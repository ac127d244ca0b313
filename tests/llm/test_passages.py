"""Repeated passages, against a brute-force version and wherever they begin and end."""

import random
import re

import numpy as np
import pytest

from tmotif.llm import substring

SCHEMA = "doc_id bigint, text string, at int, d string, marks string"


def brute_parts(text: str, reach: int) -> list[str]:
    """By its definition: each window of words picks the beginning of a sentence, or the smallest hash."""
    import xxhash

    found = list(re.finditer(r"[^\x20\x09-\x0D]+", text))
    if not found:
        return [text] if text else []
    begins = [k == 0 or "\n" in text[found[k - 1].end() : m.start()] or found[k - 1][0][-1] in ".!?" for k, m in enumerate(found)]
    rank = [(not b, xxhash.xxh32_intdigest(m[0].encode()) >> 1, -k) for k, (m, b) in enumerate(zip(found, begins, strict=True))]
    cut = {0} | {-min(rank[i : i + reach])[2] for i in range(len(found) - reach + 1)}
    edges = [0, *(found[k].start() for k in sorted(cut - {0})), len(text)]
    return [text[a:b] for a, b in zip(edges, edges[1:], strict=False)]


def brute(texts: dict[int, str | None], reach: int, least: int) -> dict[int, tuple[int, list[int], str]]:
    seen: dict[tuple, tuple] = {}
    out = {}
    for d in sorted(texts):
        parts = brute_parts(texts[d] or "", reach)
        words = [p.split() if p.strip(" \t\n\r\x0b\x0c") else [] for p in parts]
        gone = set()
        for i in range(len(parts)):
            run, k = [], i
            while k < len(parts) and len(run) < least:
                run += words[k]
                k += 1
            if len(run) >= least and seen.setdefault(tuple(run), (d, i)) != (d, i):
                gone |= set(range(i, k))
        out[d] = len(parts) if any(words) else 0, sorted(gone), "".join(p for i, p in enumerate(parts) if i not in gone)
    return out


def some_words(rnd: random.Random, n: int) -> list[str]:
    return ["".join(rnd.choice("abcdefghé") for _ in range(rnd.randint(1, 8))) + rnd.choice(["", "", "", "", ",", ".", "!\n", "\n"]) for _ in range(n)]


@pytest.fixture(scope="module")
def texts():
    rnd = random.Random(8)
    passage = some_words(rnd, 90)
    out = {d: " ".join(some_words(rnd, rnd.randint(1, 150) if d % 4 else 40)) for d in range(30)}
    for d in (3, 7, 11, 19):
        a, b = rnd.randint(0, 20), rnd.randint(75, 90)
        out[d] = f"{out[d]} {' '.join(passage[a:b])} {out[d + 1]}"
    out |= {40: None, 41: "", 42: " \n\t ", 43: "word", 44: out[4], 45: "a b c d e f g h i j k l. " * 9, 46: "buy " * 300, 47: " \n" + out[8] + " \t", 48: "x" * 5000}
    out[49] = " ".join(some_words(rnd, 30_000)) + " " + " ".join(passage)
    return out


def test_against_brute_force(spark, texts):
    df = spark.createDataFrame([(d, t, 1, "x", "y") for d, t in texts.items()], SCHEMA).repartition(3)
    for reach, least in ((substring.REACH, substring.LEAST_WORDS), (4, 7)):
        want = brute(texts, reach, least)
        got = {r["doc_id"]: (r["n_parts"], r["removed"], r["text"]) for r in substring.remove_repeated_spans(df, reach=reach, least_words=least).collect()}
        assert got == want
        assert all(want[d][1] for d in (7, 11, 19, 44, 46, 47, 49))
    assert substring.remove_repeated_spans(df.where("false")).count() == 0


def test_ids(spark):
    """Null ids come last, repeated rows are one document."""
    rnd = random.Random(3)
    long, other = " ".join(some_words(rnd, 80)), " ".join(some_words(rnd, 80))
    rows = [(5, long), (5, long), (4, other), (None, long), (None, long), (None, None), (None, other + " " + " ".join(some_words(rnd, 9))), (4, other), (9, long)]
    got = substring.remove_repeated_spans(spark.createDataFrame([(d, t, 1, "", "") for d, t in rows], SCHEMA)).collect()
    assert len(got) == len(rows)
    for r in got:
        if r["doc_id"] in (4, 5):
            assert not r["removed"] and r["text"] in (long, other)
        elif r["doc_id"] == 9:
            assert r["removed"] and len(r["text"]) < len(long) / 2
        else:
            assert r["removed"] or r["text"] == ""


def test_no_passage_is_missed():
    """Of 51 words in common, whatever stands around them, most are found; other documents keep all."""
    rnd = random.Random(21)
    for _ in range(300):
        common = some_words(rnd, 51)
        a, b = (" ".join([*some_words(rnd, rnd.randint(0, 60)), *common, *some_words(rnd, rnd.randint(0, 60))]).encode() for _ in "ab")
        first = substring.runs_of(a)[2][:, 0]
        starts, ends, hashes = substring.runs_of(b)
        gone = substring.covered_parts(starts, ends, hashes, first)
        assert sum(starts[k + 1] - starts[k] for k in gone) >= substring.LEAST_WORDS
        starts, ends, hashes = substring.runs_of(" ".join(some_words(rnd, 200)).encode())
        assert not len(substring.covered_parts(starts, ends, hashes, first))


def test_half_of_each_passage(spark):
    rnd = random.Random(22)
    texts, inside = {}, {}
    for k in range(25):
        passage = some_words(rnd, 55 + 10 * (k % 4))
        for d in (2 * k, 2 * k + 1):
            texts[d] = " ".join([*some_words(rnd, rnd.randint(3, 60)), *passage, *some_words(rnd, rnd.randint(3, 60))])
        inside[2 * k + 1] = len(passage)
    df = spark.createDataFrame([(d, t, 1, "", "") for d, t in texts.items()], SCHEMA).repartition(3)
    for r in substring.remove_repeated_spans(df).collect():
        lost = len(texts[r["doc_id"]].split()) - len(r["text"].split())
        assert lost == 0 if r["doc_id"] not in inside else inside[r["doc_id"]] / 2 <= lost <= inside[r["doc_id"]]


def test_equal_words_and_few():
    assert substring.part_starts([b"a"] * 30, np.zeros(30, bool), 10).tolist() == [0, *range(9, 31)]
    assert substring.part_starts([b"a", b"b"], np.array([True, False]), 10).tolist() == [0, 2]
