"""Near copies in groups far larger than a crowd, against brute force."""

import random

import numpy as np
import pytest
from brute import components

from tmotif.llm import simhash


def brute_kept(texts: dict[int, str]) -> set[int]:
    sets = {d: set(simhash.shingle_hashes(t.encode(), 5).tolist()) for d, t in texts.items()}
    want = components(list(texts), lambda a, b: len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]))
    return {d for d in texts if want[d] == d}


def star(n: int, words: int = 200, changed: int = 4) -> dict[int, str]:
    """Near copies of a base that comes last; each is near to the base only."""
    rnd = random.Random(11)
    base = [f"w{i}" for i in range(words)]
    out = {}
    for d in range(n):
        copy = list(base)
        for k in range(changed):
            copy[rnd.randrange(k * words // changed + 6, (k + 1) * words // changed - 6)] = f"x{d}y{k}"
        out[d] = " ".join(copy)
    return out | {n: " ".join(base)}


@pytest.mark.parametrize("rows", [2048, 90])
def test_star_of_near_copies(spark, monkeypatch, rows):
    monkeypatch.setattr(simhash, "BLOCK_ROWS", rows)
    texts = star(300) | {1000 + k: " ".join(f"z{k}q{i}" for i in range(50)) for k in range(5)}
    want = brute_kept(texts)
    assert len(want) == 6
    df = spark.createDataFrame(list(texts.items()), "doc_id bigint, text string").repartition(3)
    assert {r["doc_id"] for r in simhash.drop_near_copies(df).collect()} == want


def test_short_near_copies(spark):
    """Texts of few shingles, with a word more or less at the end or another one in place of it."""
    rnd = random.Random(12)
    texts = {}
    for d in range(0, 600, 2):
        words = [f"v{rnd.randrange(10**6)}" for _ in range(rnd.randint(5, 90))]
        texts[d + 1] = " ".join(words)
        texts[d] = " ".join(words + [f"u{d}"] if d % 4 else [*words[:-1], f"u{d}"])
    texts |= {700 + k: "one line that many short texts start with " + f"k{k} m{k} n{k}" for k in range(100)}
    want = brute_kept(texts)
    assert 400 < len(want) < 600
    df = spark.createDataFrame(list(texts.items()), "doc_id bigint, text string").repartition(3)
    assert {r["doc_id"] for r in simhash.drop_near_copies(df).collect()} == want


def test_prefix_meets():
    rnd = random.Random(13)
    for _ in range(300):
        common = [rnd.getrandbits(64) for _ in range(rnd.randint(1, 80))]
        a, b = (np.unique(np.array(common + [rnd.getrandbits(64) for _ in range(rnd.randint(0, 1 + len(common) // 5))], np.uint64)) for _ in "ab")
        both = len(np.intersect1d(a, b))
        if both >= 0.8 * (len(a) + len(b) - both):
            assert np.isin(simhash.prefix_of(a, 0.8), simhash.prefix_of(b, 0.8)).any()
