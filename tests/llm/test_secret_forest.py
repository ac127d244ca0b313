"""The secret scan against a plain version, and what it finds in the given documents."""

import random

import pytest
import regex

from tmotif.llm import secrets

SF = "/root/testdata/sf0.01"


def plain_features(text: str, left: str, right: str, words: str) -> dict[str, float]:
    n = max(1, len(text))
    has = lambda pattern, x: float(bool(regex.search(pattern, x)))
    return {
        "length": float(len(text)),
        "transitions": len(regex.findall("[a-z](?=[A-Z0-9])|[A-Z](?=[a-z0-9])|[0-9](?=[A-Za-z])", text)) / n,
        "dictionary": (len(text) - len(regex.sub(words, "", text))) / n,
        "path": float(bool(regex.search(r"^[./~]|/.*/|\.[a-z]{2,4}\Z|^www", text) or regex.search(r"[/\\@:]\Z", left) or regex.search(r"^[/\\@]", right))),
        "secret_word": has(secrets.SECRET_WORD, left),
        "harmless_word": has(secrets.HARMLESS_WORD, left),
        "digits": len(regex.findall("[0-9]", text)) / n,
        "distinct": len(set(text)) / n,
        "known": float(any(regex.search(p.replace("$", r"\Z"), text) for _, p in secrets.KINDS)),
        "mixed": has("[a-z]", text) + has("[A-Z]", text) + has("[0-9]", text),
    }


def plain_scan(text: str | None, forest: list, words: str = secrets.DICTIONARY) -> tuple[int, list, str | None]:
    """Candidates one by one, each tree walked."""

    def walk(node, f):
        while isinstance(node, tuple):
            node = node[2] if f[secrets.FEATURES[node[0]]] <= node[1] else node[3]
        return node

    kept, out, at, n, before = [], "", 0, 0, 0
    found = [m for m in regex.finditer(secrets.CANDIDATE, text or "")]
    for k, m in enumerate(found):
        n += 1
        after = found[k + 1].start() if k + 1 < len(found) else len(text)
        f = plain_features(m[0], text[before : m.start()][-secrets.BESIDE :], text[m.end() : after][: secrets.BESIDE], words)
        before = m.end()
        score = sum(walk(t, f) for t in forest) / len(forest)
        if score >= 0.5:
            kind = next((name for name, p in secrets.KINDS if regex.search(p.replace("$", r"\Z"), m[0])), "generic")
            kept.append((m.start(), len(m[0]), kind))
            out += text[at : m.start()] + f"[{kind}]"
            at = m.end()
    return n, kept, None if text is None else out + text[at:]


def odd_texts() -> list[str | None]:
    rnd = random.Random(12)
    pick = lambda letters, a, b: "".join(rnd.choice(letters) for _ in range(rnd.randint(a, b)))
    hexa, every = "0123456789abcdef", "abcdefXYZ0189+/_.~-=é"
    parts = [lambda: pick(hexa, 32, 40), lambda: pick(every, 3, 50), lambda: "password = " + pick(every, 4, 14), lambda: 'token: "' + pick(hexa, 8, 40) + '"', lambda: "commit " + pick(hexa, 40, 40), lambda: "/".join(["http:/", "www.site.com", "page", pick(hexa, 3, 20)]), lambda: "AKIA" + pick("ABCDEF0123", 16, 16), lambda: "-----BEGIN PRIVATE KEY-----\n" + pick(hexa + "\n", 20, 90) + "\n-----END PRIVATE KEY-----", lambda: "plain words 中文 here.", lambda: "card 1234567812345678"]
    out: list[str | None] = [" ".join(rnd.choice(parts)() for _ in range(rnd.randint(1, 6))) for _ in range(250)]
    return [*out, None, "", " ", "x" * 9000 + " 1" * 500, "token=" + "a1" * 20_000, out[0], out[0]]


def test_scan_against_plain(spark):
    forest = secrets.default_forest(spark)
    texts = odd_texts()
    df = spark.createDataFrame([(k, t, 1) for k, t in enumerate(texts)] + [(None, texts[3], 1), (None, texts[3], 1)], "doc_id bigint, text string, found int").repartition(3)
    rows = secrets.scan(df).collect()
    assert len(rows) == len(texts) + 2
    for r in rows:
        text = texts[3 if r["doc_id"] is None else r["doc_id"]]
        assert (r["n_candidates"], [(s["start"], s["length"], s["kind"]) for s in r["secrets"]], r["redacted"]) == plain_scan(text, forest), text
    assert sum(bool(r["secrets"]) for r in rows) > 50


def test_given_documents(spark):
    """Findings labelled from the tables, held out: precision and recall of the forest, and of the scan on whole documents."""
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    words = secrets.learned_words(docs, 100)
    assert 50 < len(words) <= 100 and "tion" in words
    labelled = secrets.table_findings(docs).collect()
    assert {r["label"] for r in labelled} == {0, 1} and len(labelled) > 40
    rows = secrets.scan(docs).select("doc_id", "secrets").collect()
    true = {(r["doc_id"], r["candidate"]) for r in labelled if r["label"]}
    false = {(r["doc_id"], r["candidate"]) for r in labelled if not r["label"]}
    got = {(r["doc_id"], s["text"]) for r in rows for s in r["secrets"]}
    recall, precision = len(got & true) / len(true), len(got & true) / max(1, len(got & (true | false)))
    assert recall >= 0.98 and precision >= 0.98


def test_learned_dictionary(spark):
    """A forest grown with words of the documents, half the labels held out."""
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    words = secrets.dictionary_of(secrets.learned_words(docs, 100))
    labels = secrets.labelled_findings() + secrets.named_findings()
    random.Random(1).shuffle(labels)
    half = len(labels) // 2
    forest = secrets.grow(secrets.findings_table(spark, labels[:half]), words=words)
    table = secrets.findings_table(spark, labels[half:]).selectExpr("monotonically_increasing_id() doc_id", "concat(left, candidate, right) text", "label")
    got = {r["doc_id"]: bool(r["secrets"]) for r in secrets.scan(table, forest, words=words).collect()}
    truth = {r["doc_id"]: bool(r["label"]) for r in table.collect()}
    hits = sum(got[d] and truth[d] for d in truth)
    assert hits / sum(truth.values()) > 0.9 and hits / sum(got.values()) > 0.85
    sample = docs.limit(60).collect()
    for r in secrets.scan(docs.where(docs.doc_id.isin([x["doc_id"] for x in sample])), forest, words=words).collect():
        text = next(x["text"] for x in sample if x["doc_id"] == r["doc_id"])
        assert (r["n_candidates"], [(s["start"], s["length"], s["kind"]) for s in r["secrets"]], r["redacted"]) == plain_scan(text, forest, words)


def test_empty(spark):
    df = spark.createDataFrame([], "doc_id bigint, text string")
    assert secrets.scan(df).count() == 0 and secrets.table_findings(df).count() == 0 and secrets.learned_words(df) == []
    with pytest.raises(ValueError):
        secrets.grow(secrets.table_findings(df))
