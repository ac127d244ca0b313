"""The pipeline on the smallest tables: stages keep the columns, the sum equals stage by stage application."""

import math
import random
from collections import Counter

import duckdb
import public_tokenizers
from brute import components, crc, exact
from test_operators import kn_brute
from test_secret_forest import plain_scan
from tokenizers import Tokenizer

import corpus_pipeline
from tmotif.llm import packing, quality, queries, secrets

SF = "/root/testdata/sf0.001"


def test_pipeline(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, seen = docs.columns, [docs.count()]
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, SF)
        assert docs.columns == columns
        seen.append(docs.count())
    assert seen == sorted(seen, reverse=True)
    pieces = corpus_pipeline.run(spark, SF)
    assert pieces.select("doc_id").distinct().count() == seen[-1]


def corpus() -> dict[int, tuple[str | None, str | None]]:
    """Clean texts, junk, exact copies, more near copies of one text than a crowd, secrets, empty and null texts."""
    rnd = random.Random(17)
    words = ["the", "of", "river", "stone", "green", "walk", "house", "bread", "small", "light", "never", "and"]
    some = lambda n: [rnd.choice(words) for _ in range(n)]
    out: dict[int, tuple[str | None, str | None]] = {d: (" ".join(some(rnd.randint(20, 120))) + ".", "en") for d in range(60)}
    base = some(150)
    for d in range(100, 180):
        copy = list(base)
        for k in range(3):
            copy[rnd.randrange(50 * k + 6, 50 * k + 44)] = rnd.choice(words)
        out[d] = " ".join(copy), "en"
    out[180] = " ".join(base), "en"
    for d in range(200, 215):
        out[d] = "".join(rnd.choice("#$%|&*QXZ0123456789") for _ in range(200)), "en"
    for d in range(220, 230):
        out[d] = out[d - 200][0].replace(" ", "  ", 3) + " ", "en"
    for d in range(240, 260):
        out[d] = f"{out[d - 210][0]} token: {rnd.randbytes(20).hex()} and {' '.join(some(30))}", "en"
    return out | {300: (None, "en"), 301: ("", None), 302: (out[7][0], None), 303: ("die Stadt und der Fluss", "de"), 304: ("", "en")}


def test_against_brute_force(spark, tmp_path):
    """All five stages, each on what its own predecessor kept."""
    docs, order = corpus(), quality.ORDER
    trusted = [d for d in docs if d < 50 or 100 <= d < 130 or 240 <= d < 250]
    spark.createDataFrame([(d, t, x, "s", len(t or "")) for d, (t, x) in docs.items()], "doc_id bigint, text string, lang string, source string, n_chars bigint").repartition(4).write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(d, 1, 0) for d in trusted] + [(205, 0, 0)], "doc_id bigint, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    # texts without a model of their language take the one of all trusted texts, here the same
    p = kn_brute([docs[d][0] for d in trusted], order)
    score = {d: math.exp(-sum(map(math.log, p(t))) / len(t)) for d, (t, _) in docs.items() if t}
    limit = sorted(score[d] for d in trusted)[math.ceil(quality.QUANTILE * len(trusted)) - 1]
    good = {d: docs[d][0] for d in docs if d in score and score[d] <= limit + 1e-9}
    firsts = {d: t for d, t in good.items() if exact(good)[d][2]}
    assert not any(200 <= d < 215 for d in good) and 302 in good and 302 not in firsts
    shingles = lambda t: {tuple(w[i : i + 5]) for w in [t.lower().split()] for i in range(max(1, len(w) - 4))}
    sets = {d: shingles(t) for d, t in firsts.items()}
    roots = components(sorted(sets), lambda a, b: len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]))
    single = {d: t for d, t in firsts.items() if roots[d] == d}
    assert sum(100 <= d <= 180 for d in firsts) > 64 and sum(100 <= d <= 180 for d in single) < 10
    forest = secrets.default_forest(spark)
    clean = {d: plain_scan(t, forest)[2] for d, t in single.items()}
    assert sum(clean[d] != t for d, t in single.items()) >= 5
    seen, rows = [good, firsts, single, clean], spark.read.parquet(str(tmp_path / "documents.parquet"))
    for (_, stage), want in zip(corpus_pipeline.STAGES, seen, strict=False):
        rows = stage(spark, rows, str(tmp_path))
        rows.write.parquet(str(tmp_path / f"stage{len(want)}-{id(want)}"))
        rows = spark.read.parquet(str(tmp_path / f"stage{len(want)}-{id(want)}"))
        assert {r["doc_id"]: r["text"] for r in rows.collect()} == want
    library = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    ids = {d: [*library.encode(t, add_special_tokens=False).ids, 1] for d, t in clean.items()}
    pieces = corpus_pipeline.run(spark, str(tmp_path)).collect()
    held: dict[int, list] = {}
    for r in pieces:
        own = ids[r["doc_id"]][r["start"] : r["start"] + r["length"]]
        assert len(own) == r["length"] and crc(own) == r["ids_crc32"] and r["doc_tokens"] == len(ids[r["doc_id"]])
        held.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    assert Counter(r["doc_id"] for r in pieces for _ in range(r["length"])) == Counter({d: len(x) for d, x in ids.items()})
    for some in held.values():
        assert [a for a, _ in sorted(some)] == [sum(n for _, n in sorted(some)[:k]) for k in range(len(some))] and sum(n for _, n in some) <= 2048
    assert len(held) == sum(n for _, n in packing.pack_histogram(Counter(r["length"] for r in pieces)))


def test_sql(spark):
    con = duckdb.connect()
    for t in ("documents", "pages"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    for name, sql in queries.oracle_sql().items():
        df = queries.queries()[name](spark, SF)
        want = con.execute(sql)
        order = [c[0] for c in want.description]
        assert sorted(df.columns) == sorted(order)
        assert sorted(map(repr, (tuple(r) for r in df.select(*order).collect()))) == sorted(map(repr, want.fetchall()))
