"""Each operator against a brute-force version or an exact round trip, on a fixture with every awkward case."""

import hashlib
import json
import random
from collections import Counter

import numpy as np
import public_tokenizers
import pytest
from brute import components, crc, exact, rules, simhash_components, url
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from tmotif.llm import binary, bpe, common, packing, quality, secrets, simhash, urls
from tmotif.llm import exact as exact_op
from tmotif.llm import rules as rules_op

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars int, row int, fp string, hash string, rank int, part string"


def texts() -> dict[int, str | None]:
    rnd = random.Random(5)
    words = ["the", "of", "and", "alpha", "Beta", "gamma,", "delta.", "straße", "été", "ΑΣ", "12", "x9!", "中文", "don't", "\u0301a", "a\u00a0b", "<|endoftext|>"]
    out: dict[int, str | None] = {0: None, 1: "", 2: " \n\t ", 3: "one", 4: "two words", 5: "A  b\nc", 6: "a b c", 7: "A b c", 8: "x" * 9000, 9: "\x1cq\x85r \u3000s"}
    base = " ".join(rnd.choice(words) for _ in range(300)) + "."
    for d in range(10, 60):
        out[d] = " ".join(rnd.choice(words) + rnd.choice(["", "\n", ". "]) for _ in range(rnd.randint(1, 120)))
    for d in range(60, 80):
        out[d] = base.replace("alpha", "alpha", 1) if d % 2 else base + f" tail{d}"
    out[80] = ("same line here\n" * 70) + "end"
    out[81] = " ".join(f"w{i}" for i in range(21_000))
    return out


TEXTS = texts()


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(d, t, None if d % 7 == 0 else ("en", "de", "zz")[d % 3], None, None, d, "q", "h", 1, "p") for d, t in TEXTS.items()]
    return spark.createDataFrame(rows, SCHEMA).repartition(5)


@pytest.fixture(scope="module")
def empty(docs):
    return docs.where("false")


@pytest.fixture(scope="module")
def odd(spark):
    """Null ids, repeated rows, ties."""
    rows = [(None, "same text here", *[None] * 8), (None, "same text here", *[None] * 8), (5, "same text here", *[None] * 8), (5, "same text here", *[None] * 8), (4, "other", *[None] * 8), (4, "other", *[None] * 8), (None, None, *[None] * 8)]
    return spark.createDataFrame(rows, SCHEMA)


def by_id(df):
    return {r["doc_id"]: r for r in df.collect()}


def test_simhash(docs, empty, odd):
    got, want = by_id(simhash.simhash_groups(docs)), simhash_components(TEXTS)
    assert {d: (r["fingerprint"], r["component_id"]) for d, r in got.items()} == want
    assert simhash.simhash_groups(empty).count() == 0
    rows = simhash.simhash_groups(odd).collect()
    assert len(rows) == 7 and {r["component_id"] for r in rows if r["group_size"] == 4} == {5}


def test_simhash_crowds(spark):
    rnd = random.Random(2)
    base = [rnd.getrandbits(64) for _ in range(3)]
    prints = {b ^ (1 << rnd.randrange(64)) ^ (1 << rnd.randrange(64)) for b in base for _ in range(150)} | set(base) | {rnd.getrandbits(64) for _ in range(200)}
    signed = [int(np.uint64(p).astype(np.int64)) for p in prints]
    df = spark.createDataFrame([(p,) for p in signed], "fp bigint")
    want = components(signed, lambda a, b: bin((a ^ b) & (2**64 - 1)).count("1") <= 2)
    for segments, crowd in ((16, 64), (8, 8), (16, 2)):
        got = {r["node"]: r["root"] for r in common.components(simhash.links(df, 2, segments, crowd)).collect()}
        assert {p: got.get(p, p) for p in signed} == want
    three = {r["node"]: r["root"] for r in common.components(simhash.links(df, 3, 16)).collect()}
    assert {p: three.get(p, p) for p in signed} == components(signed, lambda a, b: bin((a ^ b) & (2**64 - 1)).count("1") <= 3)


def test_components(spark):
    rnd = random.Random(1)
    pairs = [(rnd.randrange(400), rnd.randrange(400)) for _ in range(250)] + [(k, k + 1) for k in range(1000, 1300)]
    got = {r["node"]: r["root"] for r in common.components(spark.createDataFrame(pairs, "a bigint, b bigint").repartition(7)).collect()}
    nodes = sorted({x for p in pairs for x in p})
    linked = {frozenset(p) for p in pairs}
    want = components(nodes, lambda a, b: frozenset((a, b)) in linked)
    assert {n: got.get(n, n) for n in nodes} == want


def test_near_copies(docs, empty, odd):
    kept = {r["doc_id"] for r in simhash.drop_near_copies(docs).collect()}
    sets = {d: set(simhash.shingle_hashes((t or "").encode(), 5).tolist()) for d, t in TEXTS.items()}
    near = lambda a, b: sets[a] == sets[b] or len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])
    want = components(list(TEXTS), near)
    assert kept == {d for d in TEXTS if want[d] == d}
    assert simhash.drop_near_copies(docs).columns == docs.columns and simhash.drop_near_copies(empty).count() == 0
    assert sorted(str(r["doc_id"]) for r in simhash.drop_near_copies(odd).collect()) == ["4", "5", "None"]


def test_exact(docs, empty, odd):
    got = by_id(exact_op.exact_dedup(docs))
    assert {d: (r["keep_id"], r["group_size"], r["kept"], r["text_sha256"]) for d, r in got.items()} == exact(TEXTS)
    assert exact_op.exact_dedup(empty).count() == 0
    rows = exact_op.exact_dedup(odd).collect()
    assert sum(r["kept"] for r in rows) == 3 and {r["keep_id"] for r in rows} == {5, 4, None}
    assert exact_op.drop_exact_copies(odd).columns == odd.columns and exact_op.drop_exact_copies(odd).count() == 3
    assert {r["doc_id"] for r in exact_op.drop_exact_copies(docs).collect()} == {d for d, r in exact(TEXTS).items() if r[2]}


def test_tree_merge_rounds(docs):
    """More nodes than one round takes."""
    got = by_id(exact_op.exact_dedup(docs.repartition(40)))
    assert {d: (r["keep_id"], r["group_size"], r["kept"], r["text_sha256"]) for d, r in got.items()} == exact(TEXTS)


def test_packing(docs, empty):
    path = public_tokenizers.path("byte_bpe_50k.json")
    ids = {d: Tokenizer.from_file(path).encode(t or "", add_special_tokens=False).ids + [1] for d, t in TEXTS.items()}
    pieces = packing.pack_documents(docs, path, size=256, with_ids=True)
    rows = pieces.collect()
    whole = {d: [] for d in ids}
    for r in sorted(rows, key=lambda r: (r["doc_id"], r["start"])):
        assert r["start"] == len(whole[r["doc_id"]]) and r["doc_tokens"] == len(ids[r["doc_id"]])
        piece = np.frombuffer(r["ids"], "<u4").tolist()
        assert crc(piece) == r["ids_crc32"] and len(piece) == r["length"]
        whole[r["doc_id"]] += piece
    assert whole == ids
    seqs: dict = {}
    for r in rows:
        seqs.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for parts in seqs.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 256
    assert {r["sequence_id"]: r["n_tokens"] for r in packing.sequences(pieces).collect()} == {s: sum(n for _, n in p) for s, p in seqs.items()}
    assert packing.padding(pieces, 256).first()["padding_share"] < 0.05
    assert packing.pack_documents(empty, path).count() == 0


def test_packing_odd(odd):
    """Null ids and repeated rows are documents of their own."""
    path = public_tokenizers.path("byte_bpe_50k.json")
    library = Tokenizer.from_file(path)
    sizes = {t: len(library.encode(t or "", add_special_tokens=False).ids) + 1 for t in ("same text here", "other", None)}
    rows = packing.pack_documents(odd, path).collect()
    assert sorted((str(r["doc_id"]), r["doc_tokens"]) for r in rows) == sorted((str(r["doc_id"]), sizes[r["text"]]) for r in odd.collect())
    placed = sorted((r["offset"], r["length"]) for r in rows)
    assert {r["sequence_id"] for r in rows} == {0} and [at for at, _ in placed] == [sum(n for _, n in placed[:k]) for k in range(len(placed))]


def test_pack_histogram():
    rnd = random.Random(0)
    for _ in range(30):
        counts = {rnd.randint(1, 64): rnd.randint(1, 50) for _ in range(rnd.randint(1, 40))}
        used: dict[int, int] = {}
        for lengths, n in packing.pack_histogram(counts, 64):
            assert sum(lengths) <= 64 and n > 0
            for x in lengths:
                used[x] = used.get(x, 0) + n
        assert used == counts


def test_token_files(docs, empty, odd, tmp_path):
    path = public_tokenizers.path("word_bpe_49k.json")
    library = Tokenizer.from_file(path)
    got, at = by_id(binary.token_file_index(docs, path)), 0
    for d in sorted(TEXTS):
        ids = library.encode(TEXTS[d] or "", add_special_tokens=False).ids + [2]
        assert (got[d]["start"], got[d]["n_tokens"], got[d]["ids_crc32"]) == (at, len(ids), crc(ids))
        at += len(ids)
    assert binary.token_file_index(empty, path).count() == 0
    rows = sorted(binary.token_file_index(odd, path).collect(), key=lambda r: r["start"])
    assert [r["doc_id"] for r in rows] == [4, 4, 5, 5, None, None, None]
    names = binary.export_segments(binary.write_token_files(docs, path), str(tmp_path))
    ids = np.concatenate([binary.read_segment(open(n, "rb").read())[2] for n in names])
    assert len(ids) == at


def test_blocks():
    rng = np.random.default_rng(0)
    for ids in (np.zeros(0, np.uint32), np.array([2**32 - 1, 0], np.uint32), rng.integers(0, 300, 5000).astype(np.uint32), np.where(rng.random(3000) < 0.02, 2**31, rng.integers(0, 9, 3000)).astype(np.uint32), np.full(1025, 7, np.uint32)):
        image = binary.write_segment([1], [len(ids)], ids)
        assert np.array_equal(binary.read_segment(image)[2], ids)
        if len(ids) > 2048:
            assert np.array_equal(binary.block_of(image, 1), ids[1024:2048])


@pytest.mark.parametrize(("url_", "want"), [("http://A.Example.NET/en/x?y", ("a.example.net", "/en/x", "example.net/en/", "allow")), ("http://example.net", ("example.net", "", None, "allow")), ("x://example.com/de/#/", ("example.com", "/de/", "example.com/de/", "block"))])
def test_url_cases(url_, want):
    assert url(url_) == want


def test_urls(spark):
    rnd = random.Random(3)
    parts = ["http://", "://", "net", "example.net", "example.com", "org", "a.", "EXAMPLE.", "/", "/en/", "/de/", "/fr/", "?x=://net/", "#", "\n", "xnet", ":80"]
    cases = [None, "", "net/", "a://", "://net/", "http://net/", "http://b.net/q"] + ["".join(rnd.choice(parts) for _ in range(rnd.randint(1, 6))) for _ in range(400)]
    pages = spark.createDataFrame([(i, u, "x", "y") for i, u in enumerate(cases)], "page_id bigint, url string, host string, rule string")
    got = {r["page_id"]: tuple(r)[1:] for r in urls.filter_urls(pages).collect()}
    assert got == {i: url(u) for i, u in enumerate(cases)}
    many = [*urls.RULES, *[("block", f"h{i}.test", "/p/") for i in range(100)]]
    assert {r["page_id"]: tuple(r)[1:] for r in urls.filter_urls(pages, many).collect()} == got
    assert urls.filter_urls(pages.where("false")).count() == 0


def test_bpe(docs, empty):
    path = public_tokenizers.path("word_bpe_49k.json")
    library = Tokenizer.from_file(path)
    for d, r in by_id(bpe.bpe_round_trip(docs, path, with_text=True)).items():
        ids = library.encode(TEXTS[d] or "", add_special_tokens=False).ids
        back = library.decode(ids, skip_special_tokens=False)
        assert r["ids"] == ids and r["decoded"] == back and r["n_tokens"] == len(ids)
        assert r["ids_sha256"] == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest() and r["decoded_sha256"] == hashlib.sha256(back.encode()).hexdigest()
    assert bpe.bpe_round_trip(empty, path).count() == 0


def test_transducer():
    t = bpe.transducer(public_tokenizers.path("word_bpe_49k.json"))
    model = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json")).model
    rnd = random.Random(4)
    for k in range(300):
        piece = "".join(rnd.choice("aeinst" if k % 2 else "abcdefghijklmnopqrstuvwxyz") for _ in range(rnd.randint(1, 400)))
        want = [x.value for x in model.tokenize(piece)]
        assert [*t.stream(piece, 3)] == want == t._merged([*piece[:-1], piece[-1] + "</w>"])
    assert t.lookahead < 1000


def test_lookahead_of_hostile_merge_lists(tmp_path):
    """Chains of merges that reach far to the right: what the window gives is what the whole piece gives."""
    rnd = random.Random(14)
    far = 0
    for case in range(60):
        tokens, merges = [*"abc"], []
        if case % 3 == 0:  # each merge takes the left part of the one before it away
            for k in range(8):
                pair = (tokens[-1] if k else "a", rnd.choice("abc"))
                merges.insert(0, pair)
                tokens.append("".join(pair))
            merges = [m for m in merges if m[0] in "abc"] + [m for m in merges[::-1] if m[0] not in "abc"]
        while len(merges) < 40:
            pair = rnd.choice(tokens), rnd.choice(tokens)
            if len(pair[0] + pair[1]) <= 9 and pair not in merges:
                merges.append(pair)
                tokens.append(pair[0] + pair[1])
        vocab = {t: n for n, t in enumerate(dict.fromkeys([*"abc", *(a + b for a, b in merges)]))}
        path = tmp_path / f"{case}.json"
        path.write_text(json.dumps({"model": {"vocab": vocab, "merges": merges}}))
        t = bpe.Transducer(str(path))
        far = max(far, t.lookahead)
        for letters in ("abc", "ab", "aab", "a"):
            piece = "".join(rnd.choice(letters) for _ in range(rnd.randint(1, 300)))
            whole = t._merged([*piece])
            assert [*t.stream(piece, 1)] == whole and t.encode(piece) == [vocab[x] for x in whole]
    assert far > 12


def test_bpe_odd(odd):
    path = public_tokenizers.path("word_bpe_49k.json")
    rows = bpe.bpe_round_trip(odd, path).collect()
    assert sorted(str(r["doc_id"]) for r in rows) == ["4", "4", "5", "5", "None", "None", "None"]
    assert len({r[1:] for r in rows if r["doc_id"] == 5}) == 1 and sum(r["n_tokens"] == 0 for r in rows) == 1


def test_decoder_state():
    d = bpe.Decoder(public_tokenizers.path("byte_bpe_50k.json"))
    library = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    for text in ("été 中文 \U0001f600!", "plain"):
        ids = library.encode(text, add_special_tokens=False).ids
        assert "".join(d.stream(ids)) == text == library.decode(ids)
        assert "".join(d.stream(ids[1:-1])) == library.decode(ids[1:-1])


def test_rules(docs, empty):
    got = by_id(rules_op.quality_rules(docs))
    for d, r in got.items():
        assert tuple(r[c] for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")) == rules(TEXTS[d])
        assert not (r["base_failed"] and r["kept"])
    assert rules_op.quality_rules(empty).count() == 0


def test_rules_odd(odd):
    """Rows are judged one by one; nulls have no words."""
    rows = rules_op.quality_rules(odd).collect()
    want = sorted((str(r["doc_id"]), *rules(r["text"])) for r in odd.collect())
    assert sorted((str(r["doc_id"]), *(r[c] for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed"))) for r in rows) == want


def test_secrets(spark):
    forest = secrets.default_forest(spark)
    held = secrets.findings_table(spark, secrets.labelled_findings(200, seed=99))
    rows = held.selectExpr("monotonically_increasing_id() doc_id", "concat(left, candidate, right) text", "label", "0 found")
    got = secrets.scan(rows).collect()
    labels = {r["doc_id"]: r["label"] for r in rows.collect()}
    right = sum((len(r["secrets"]) > 0) == bool(labels[r["doc_id"]]) for r in got)
    assert right / len(got) > 0.9
    key = "0123456789abcdef0123456789abcdef01234567"
    df = spark.createDataFrame([(1, f'a token = "{key}" and\n token = "{key}" é', 5), (2, f"commit {key} done", 5), (3, None, 5), (4, "", 5), (5, "plain words only", 5)], "doc_id bigint, text string, secrets int")
    found = by_id(secrets.scan(df, forest))
    assert len(found[1]["secrets"]) == 2 and not found[2]["secrets"] and found[3]["redacted"] is None and found[4]["redacted"] == ""
    assert found[1]["redacted"] == 'a token = "[generic]" and\n token = "[generic]" é'
    for s in found[1]["secrets"]:
        assert df.first()["text"][s["start"] : s["start"] + s["length"]] == key
    assert secrets.redact(df, forest).columns == df.columns and secrets.redact(df, forest).count() == 5
    assert secrets.scan(df.where("false"), forest).count() == 0


def kn_brute(lines: list[str], order: int):
    """p(symbol, the order - 1 symbols before it) by the definition."""
    fold = lambda t: "\x02" * (order - 1) + "".join("0" if c in "0123456789" else c for c in t)
    tables = [Counter(fold(t)[i : i + order] for t in lines for i in range(len(t)))]
    for _ in range(order - 1):
        tables.insert(0, Counter(g[1:] for g in tables[0]))
    cuts = []
    for table in tables:
        n = [sum(c == k for c in table.values()) for k in (1, 2, 3, 4)]
        if not (n[0] and n[1] and n[2]):
            cuts.append((0.5, 0.75, 0.9))
        else:
            y = n[0] / (n[0] + 2 * n[1])
            cuts.append(tuple(max(0.1, k - (k + 1) * y * (n[k] or (k == 3)) / n[k - 1]) for k in (1, 2, 3)))

    def p(g: str) -> float:
        k = len(g)
        if not k:
            return 1 / (len(tables[0]) + 1)
        own = {x: n for x, n in tables[k - 1].items() if x[:-1] == g[:-1]}
        if not own:
            return p(g[1:])
        cut = lambda n: cuts[k - 1][min(n, 3) - 1]
        n = own.get(g, 0)
        return (max(n - cut(n), 0) if n else 0) / sum(own.values()) + sum(map(cut, own.values())) / sum(own.values()) * p(g[1:])

    return lambda text: [p(fold(text)[i : i + order]) for i in range(len(text))]


KN_LINES = {"en": ["abab abba. ab", "ba ba abc", "cab, abba! Ab 1", "aaa bbb ccc abc"] * 2 + ["abcabc"], "zh": ["中文中文字", "文字中文", "字字", "中文字中"], "": ["no name", "name no"]}


@pytest.mark.parametrize("order", [3, 5])
def test_kneser_ney(spark, order):
    df = spark.createDataFrame([(x, t) for x, ts in KN_LINES.items() for t in [*ts, None, ""]], "lang string, text string").repartition(3)
    models = quality.loaded(quality.tables(quality.count_grams(df, order), order), order)
    assert set(models) == set(KN_LINES)
    for lang, lines in KN_LINES.items():
        p = kn_brute(lines, order)
        for text in [*lines, "abba ab. zq 77", "文中字x", "a"]:
            assert np.exp(quality.log_p(quality.padded(quality.symbols(text), order), models[lang])) == pytest.approx(p(text), rel=1e-9)


def test_shards_equal_broadcast(spark, monkeypatch):
    """Tables over the bound are joined by shards: the same scores, no row lost; long texts in chunks."""
    monkeypatch.setattr(quality, "PART_ROWS", 7)
    rnd = random.Random(9)
    rows = [(d, "".join(rnd.choice("abc d.é中9") for _ in range(rnd.randint(0, 90))), rnd.choice(["en", "de", "xx", None])) for d in range(60)] + [(1, None, "en"), (1, None, "en"), (None, "ab", "en"), (7, "abc " * 5000, "de")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, lang string").withColumn("model_", F.lit(1)).withColumn("lang_", F.lit("q"))
    labels = spark.createDataFrame([(d, 1) for d in range(30) if rows[d][2] in ("en", "de")], "doc_id bigint, quality int")
    a, b = (sorted((tuple(round(x, 9) if isinstance(x, float) else x for x in r) for r in quality.classify(df, labels, largest=n).collect()), key=repr) for n in (quality.LARGEST, 0))
    assert a == b and len(a) == len(rows) and sum(r[2] is not None for r in a) > 50
    monkeypatch.setattr(quality, "CHUNK", 100)
    c = sorted((tuple(round(x, 9) if isinstance(x, float) else x for x in r) for r in quality.classify(df, labels).collect()), key=repr)
    assert c == a


def test_quality(spark, docs, empty):
    rnd = random.Random(6)
    words = ["the", "of", "and", "house", "river", "stone", "walk", "green"]
    clean = [" ".join(rnd.choice(words) for _ in range(60)) for _ in range(60)]
    junk = ["".join(rnd.choice("#$%|&*QXZ0123456789") for _ in range(300)) for _ in range(20)]
    rows = [(i, t, "en", i) for i, t in enumerate(clean + junk)] + [(100, None, "en", 1), (101, "", None, 1), (102, clean[0], None, 1)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, limit int")
    labels = spark.createDataFrame([(i, 1, 0) for i in range(40)] + [(1, 1, 0), (70, 0, 0), (None, 1, None), (5, None, None)], "doc_id bigint, quality int, toxic int")
    got = by_id(quality.classify(df, labels))
    assert all(got[i]["kept"] for i in range(60)) and not any(got[i]["kept"] for i in range(60, 80))
    assert not got[100]["kept"] and got[100]["perplexity"] is None and not got[101]["kept"] and got[102]["kept"]
    assert quality.keep_good(df, labels).columns == df.columns and quality.keep_good(df, labels).count() == 61
    assert quality.classify(empty, labels).count() == 0 and not any(r["kept"] for r in quality.classify(df, labels.where("false")).collect())
