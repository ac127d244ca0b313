"""What the classifier leaves on the driver, and the fingerprints of the near-copy stage."""

import pickle

import numpy as np
from test_operators import kn_brute

from tmotif.llm import quality, simhash


def test_driver_holds_no_slots(spark, monkeypatch):
    """The driver makes no table of its own; what arrives is the same as what it would have made."""
    texts = ["the river and the stone", "a green house 12", "die Stadt am Fluss", ""]
    df = spark.createDataFrame([("en", t) for t in texts[:2]] + [("de", texts[2])], "lang string, text string")
    model = quality.tables(quality.count_grams(df))
    want = quality.loaded(model)
    made = []
    real = quality.Table.__init__
    monkeypatch.setattr(quality.Table, "__init__", lambda self, *x: (made.append(1), real(self, *x))[1])
    packed = quality.loaded(model, make=quality.Packed)
    assert not made and quality.shared_tables(model) is not None and not made
    got = pickle.loads(pickle.dumps(packed))
    for lang in ("en", "de"):
        own = [quality.perplexities(texts, x[lang]) for x in (want, got)]
        assert own[0] == own[1]
    p = kn_brute(texts[:2], quality.ORDER)
    assert np.allclose(quality.perplexities(texts[:1], got["en"]), np.exp(-np.log(p(texts[0])).mean()))


def test_near_copies_go_through_fingerprints(spark):
    """Rows within two bits of each other are linked, equal ones through the smallest row, and nothing else is."""
    rnd = np.random.default_rng(5)
    far = [int(x) for x in rnd.integers(-(2**63), 2**63, 40)]
    prints = [*far, far[0] ^ 3, far[0], far[1] ^ (1 << 40), far[1] ^ (1 << 40) ^ 5]
    df = spark.createDataFrame([(100 + i, x) for i, x in enumerate(prints)], "row long, fp long")
    got = {tuple(r) for r in simhash.print_links(df).collect()}
    assert got == {(100, 141), (100, 140), (101, 142), (142, 143)}


def test_similar_links_use_fingerprints(spark, monkeypatch):
    """Copies that no ring chain and no prefix lets meet are met by their fingerprints alone; the exact check follows."""
    words = [f"w{k}" for k in range(300)]
    texts = [" ".join(words), " ".join(words).upper(), " ".join(reversed(words))]
    df = spark.createDataFrame(list(enumerate(texts)), "row long, text string").selectExpr("row", "row doc_id", "text")
    monkeypatch.setattr(simhash, "_chain_keys", lambda length: simhash.F.array().cast("array<long>"))
    _, found = simhash.similar_links(df)
    assert {tuple(r) for r in found.collect()} == {(0, 1)}
