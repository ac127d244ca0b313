"""Quality classifier: an interpolated modified Kneser-Ney model over characters for each language.

Trusted documents are read as sequences of code points (digits are one symbol), START standing before each.
Their n-grams are counted in each task and summed by (language, n-gram); the table of each order is joined,
by hash shards, with the totals of its contexts and the probabilities of the order below. A document's perplexity is that
under its language's model; it is kept up to a quantile of the trusted documents' perplexities in its language.

The finished tables reach the documents in one of two ways, which give the same numbers. Up to LARGEST entries they
are broadcast. Beyond, every bounded part of the documents sends its distinct n-grams once; these are joined with the
shards of all orders, and each part gets back the probabilities of its own n-grams.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.core.broadcast import Broadcast
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tmotif.llm.common import give_back, in_arrow, shuffled, staged, workers_see_package

ORDER = 5
#: The symbol before a text, what a text's own one becomes, and the symbol of all digits.
START, OTHER, DIGIT = 2, 1, ord("0")
#: Entries of all tables that may be broadcast (16 bytes each).
LARGEST = 4_000_000
#: Quantile of the trusted documents' perplexities.
QUANTILE = 0.997
#: Least discount, so that every n-gram has a chance.
LEAST_CUT = 0.1
#: Ids of trusted documents, and languages, that may be broadcast; more are joined by a shuffle.
BROADCAST_IDS, BROADCAST_LANGS = 2_000_000, 100_000
#: Documents of a part, where the tables are not broadcast; n-grams that a counting task holds for one language.
PART_ROWS, HELD = 2_000, 1_000_000
#: Characters that are looked up at once.
CHUNK = 1 << 18
#: Odd; codes of n-grams are polynomials in it modulo 2^64.
BASE = 0x9E3779B97F4A7C15
#: Stands for all languages.
ANY = "\x01any"


def symbols(text: str) -> np.ndarray:
    points = np.frombuffer(text.encode("utf-32-le", "replace"), "<u4").copy()
    points[(points >= 48) & (points <= 57)] = DIGIT
    points[points == START] = OTHER
    return points


def codes(line: np.ndarray, order: int) -> list[np.ndarray]:
    """For k = 0..order the codes of the k symbols that end at each place from order on."""
    n, power = len(line) - order, 1
    line, out = line.astype(np.uint64) + np.uint64(1), [np.zeros(max(0, len(line) - order), np.uint64)]
    for k in range(1, order + 1):
        out.append(out[-1] + line[order - k + 1 : order - k + 1 + n] * np.uint64(power))
        power = power * BASE % (1 << 64)
    return out


def padded(points: np.ndarray, order: int) -> np.ndarray:
    return np.concatenate([np.full(order, START, points.dtype), points])


def _grams(lines: list[np.ndarray], order: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct codes of the n-grams of padded lines, how often each occurs, and its symbols, a row each."""
    code = np.concatenate([codes(x, order)[order] for x in lines])
    ends = np.concatenate([np.arange(len(x) - order) + at for x, at in zip(lines, np.cumsum([0, *map(len, lines[:-1])]), strict=True)])
    distinct, first, counts = np.unique(code, return_index=True, return_counts=True)
    return distinct, counts, np.concatenate(lines)[ends[first][:, None] + np.arange(1, order + 1)]


def _counted(order: int):
    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, tuple] = {}

        def rows(lang: str) -> pa.RecordBatch:
            _, counts, chars = held.pop(lang)
            raw = np.ascontiguousarray(chars.astype("<u4")).tobytes()
            grams = [raw[k : k + 4 * order].decode("utf-32-le") for k in range(0, len(raw), 4 * order)]
            return pa.RecordBatch.from_arrays([pa.array([lang] * len(grams), pa.string()), pa.array(grams, pa.string()), pa.array(counts, pa.int64())], ["lang", "g", "c"])

        def add(lang: str, lines: list[np.ndarray]) -> None:
            new = _grams(lines, order)
            if lang in held:
                distinct, first, back = np.unique(np.concatenate([held[lang][0], new[0]]), return_index=True, return_inverse=True)
                counts = np.bincount(back, np.concatenate([held[lang][1], new[1]])).astype(np.int64)
                new = distinct, counts, np.concatenate([held[lang][2], new[2]])[first]
            held[lang] = new

        for batch in batches:
            waiting: dict[str, list[np.ndarray]] = {}
            for lang, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if text:
                    waiting.setdefault(lang, []).append(padded(symbols(text), order))
                    if sum(map(len, waiting[lang])) > CHUNK:
                        add(lang, waiting.pop(lang))
            for lang, lines in waiting.items():
                add(lang, lines)
            for lang in [x for x in held if len(held[x][0]) > HELD]:
                yield rows(lang)
        for lang in [*held]:
            yield rows(lang)

    return make


def count_grams(texts: DataFrame, order: int = ORDER) -> DataFrame:
    """lang, g (the symbols, as a string), c over all rows (lang, text)."""
    return in_arrow(texts.select("lang", "text"), _counted(order), "lang string, g string, c long").groupBy("lang", "g").agg(F.sum("c").alias("c"))


def _with_discounts(table: DataFrame) -> DataFrame:
    """Adds d, the discount of modified Kneser-Ney for the count, by language; fixed ones where a class of counts is empty."""
    sums = table.groupBy("lang").agg(*[F.sum((F.col("c") == k).cast("double")).alias(f"n{k}") for k in (1, 2, 3, 4)])
    n1, n2, n3, n4 = (F.col(f"n{k}") for k in (1, 2, 3, 4))
    y, whole = n1 / (n1 + 2 * n2), (n1 > 0) & (n2 > 0) & (n3 > 0)
    cuts = [(1 - 2 * y * n2 / n1, 0.5), (2 - 3 * y * n3 / n2, 0.75), (3 - 4 * y * F.greatest(n4, F.lit(1.0)) / n3, 0.9)]
    named = sums.select("lang", *[F.when(whole, F.greatest(F.lit(LEAST_CUT), x)).otherwise(F.lit(z)).alias(f"d{k}") for k, (x, z) in enumerate(cuts, 1)])
    return table.join(named, "lang").withColumn("d", F.when(F.col("c") == 1, F.col("d1")).when(F.col("c") == 2, F.col("d2")).otherwise(F.col("d3"))).drop("d1", "d2", "d3")


def tables(counts: DataFrame, order: int = ORDER) -> DataFrame:
    """lang, k, kind, g, v: kind 'p' has log probabilities of the n-grams seen of order k, 'w' log back-off weights of their contexts; order 0 has that of a symbol never seen.

    The highest order has counts, each lower one the number of different
    symbols before the n-gram.
    """
    every = [staged(counts, "grams")]
    for _ in range(order - 1):
        every.insert(0, every[0].groupBy("lang", F.expr("substring(g, 2)").alias("g")).agg(F.count(F.lit(1)).alias("c")))
    # a symbol that no trusted text has is one more symbol
    below = every[0].groupBy("lang").agg((1.0 / (F.count(F.lit(1)) + 1)).alias("low"))
    out = below.select("lang", F.lit(0).alias("k"), F.lit("p").alias("kind"), F.lit("").alias("g"), F.log("low").alias("v"))
    on = ["lang"]
    for k, table in enumerate(every, 1):
        rows = _with_discounts(staged(table, "grams") if k < order else table).select("lang", "g", "c", "d", F.expr(f"left(g, {k - 1})").alias("h"), F.expr("substring(g, 2)").alias("s"))
        context = staged(rows.groupBy("lang", "h").agg(F.sum("c").alias("all"), F.sum("d").alias("held")), "contexts")
        p = F.greatest(F.col("c") - F.col("d"), F.lit(0.0)) / F.col("all") + F.col("held") / F.col("all") * F.col("low")
        seen = staged(shuffled(rows).join(context, ["lang", "h"]).join(below if k == 1 else shuffled(below), on).select("lang", "g", p.alias("p")), "model")
        out = out.union(seen.select("lang", F.lit(k), F.lit("p"), "g", F.log("p"))).union(context.select("lang", F.lit(k), F.lit("w"), F.col("h"), F.log(F.col("held") / F.col("all"))))
        below, on = seen.select("lang", F.col("g").alias("s"), F.col("p").alias("low")), ["lang", "s"]
    return out


class Table:
    """Codes and their values, by open addressing: at most half of the slots is used, so that most look-ups end at the first. A slot holds the place of its code, or -1."""

    def __init__(self, keys: np.ndarray, values: np.ndarray):
        bits = max(4, int(2 * len(keys)).bit_length())
        self.shift, self.mask = np.uint64(64 - bits), np.int64((1 << bits) - 1)
        self.keys, self.values = (keys, values) if len(keys) else (np.zeros(1, np.uint64), np.zeros(1))
        self.places = np.full(1 << bits, -1, np.int32)
        slots, left = self._slots(keys), np.arange(len(keys), dtype=np.int32)
        while len(left):
            free = left[self.places[slots[left]] < 0]
            self.places[slots[free]] = free  # of several the last one stays
            left = left[self.places[slots[left]] != left]
            slots[left] = (slots[left] + 1) & self.mask

    def _slots(self, keys: np.ndarray) -> np.ndarray:
        return ((keys ^ (keys >> np.uint64(29))) * np.uint64(BASE) >> self.shift).astype(np.int64)

    def get(self, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Which are there, and the values of all (zero where not)."""
        slots = self._slots(wanted)
        at = self.places[slots]
        hit = (at >= 0) & (self.keys[at] == wanted)
        values = np.where(hit, self.values[at], 0.0)
        left = np.flatnonzero(~hit & (at >= 0))
        while len(left):
            slots[left] = (slots[left] + 1) & self.mask
            at = self.places[slots[left]]
            met = (at >= 0) & (self.keys[at] == wanted[left])
            hit[left[met]], values[left[met]] = True, self.values[at[met]]
            left = left[~met & (at >= 0)]
        return hit, values


def codes_of(grams: pa.Array, size: int) -> np.ndarray:
    """Codes of n-grams of so many symbols, given as strings; their bytes are read as one text."""
    if not size or not len(grams):
        return np.zeros(len(grams), np.uint64)
    raw = pa.concat_arrays([pa.array([""], grams.type), grams])  # a copy of its own, without what a slice leaves out
    text = raw.buffers()[2].to_pybytes()[: raw.nbytes].decode()
    points = np.frombuffer(text.encode("utf-32-le"), "<u4")[: len(grams) * size].reshape(len(grams), size)
    return codes(np.concatenate([np.zeros((len(grams), 1), np.uint32), points], axis=1).T, size)[size].reshape(-1)


def _table(grams: pa.Array, values: np.ndarray, size: int) -> Table:
    return Table(codes_of(grams, size), values)


class Packed:
    """What a Table is made of. Pickled, it arrives as the Table, so that only the workers hold the slots."""

    def __init__(self, keys: np.ndarray, values: np.ndarray):
        self.keys, self.values = keys, values

    def __reduce__(self):
        return Table, (self.keys, self.values)


def _codes_of_order(k: int):
    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for kind, size in (("p", k), ("w", k - 1)):
                own = batch.filter(pa.compute.equal(batch.column(1), kind))
                yield pa.RecordBatch.from_arrays([own.column(0), own.column(1), pa.array(codes_of(own.column(2), size).view(np.int64)), own.column(3)], ["lang", "kind", "code", "v"])

    return make


def loaded(model: DataFrame, order: int = ORDER, make: type = Table) -> dict[str, list]:
    """language -> for each order the tables of log p and of log weights; [0] is the log p of an unknown symbol. One order at a time comes to the driver, as codes and values that the workers made."""
    out: dict[str, list] = {}
    for r in model.where("k = 0").select("lang", "v").collect():
        out[r["lang"]] = [r["v"]]
    for k in range(1, order + 1):
        rows = in_arrow(model.where(f"k = {k}").select("lang", "kind", "g", "v"), _codes_of_order(k), "lang string, kind string, code long, v double").toArrow()
        for lang, tables_ in out.items():
            pair = []
            for kind in "pw":
                own = rows.filter(pa.compute.and_(pa.compute.equal(rows["lang"], lang), pa.compute.equal(rows["kind"], kind)))
                pair.append(make(own["code"].to_numpy().view(np.uint64), own["v"].to_numpy()))
            tables_.append(tuple(pair))
        del rows
    return out


def log_p(line: np.ndarray, model: list) -> np.ndarray:
    """Of each symbol of a line after those before it; the first order symbols stand for what was before and have none."""
    order = len(model) - 1
    own = codes(np.concatenate([np.full(1, START, line.dtype), line]), order)  # own[k][i + 1] ends at the symbol, own[k][i] before it
    out, need = np.zeros(max(0, len(line) - order)), np.arange(max(0, len(line) - order))
    for k in range(order, 0, -1):
        hit, values = model[k][0].get(own[k][1:] if k == order else own[k][need + 1])
        out[need] += values
        need = need[~hit]
        if not len(need):
            return out
        out[need] += model[k][1].get(own[k - 1][need])[1]
    out[need] += model[0]
    return out


def perplexities(texts: list[str | None], model: list | None) -> list[float | None]:
    """Per symbol; None for null and empty texts and where there is no model. Short texts are looked up together, long ones in parts."""
    out: list[float | None] = [None] * len(texts)
    if model is None:
        return out
    order, waiting, size = len(model) - 1, [], 0

    def done() -> None:
        line = np.concatenate([x for _, x in waiting])
        values, at = log_p(line, model), 0
        for k, x in waiting:  # each over its own values, so that a text has the same perplexity whatever it is looked up with
            n = len(x) - order
            out[k] = float(np.exp(-values[at : at + n].sum() / n))
            at += len(x)

    for k, text in enumerate(texts):
        if not text:
            continue
        points = padded(symbols(text), order)
        if len(points) > CHUNK:
            total = sum(float(log_p(points[j : j + CHUNK + order], model).sum()) for j in range(0, len(points) - order, CHUNK))
            out[k] = float(np.exp(-total / (len(points) - order)))
            continue
        waiting.append((k, points))
        size += len(points)
        if size > CHUNK:
            done()
            waiting, size = [], 0
    if waiting:
        done()
    return out


def _scored(models, text_at: int, lang_at: int):
    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = models.value
        give_back()
        for batch in batches:
            texts, of = batch.column(text_at).to_pylist(), batch.column(lang_at).to_pylist()
            scores: list[float | None] = [None] * len(texts)
            for lang in set(of):
                own = [k for k, x in enumerate(of) if x == lang]
                for k, score in zip(own, perplexities([texts[k] for k in own], known.get(lang, known.get(ANY))), strict=True):
                    scores[k] = score
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(scores, pa.float64())], [*batch.schema.names, "score"])

    return make


def _asked(order: int):
    """The distinct n-grams of each part's documents: part, lang, g."""
    count = _counted(order)

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in set(batch.column(0).to_pylist()):
                own = batch.filter(pa.compute.equal(batch.column(0), part))
                for rows in count([pa.RecordBatch.from_arrays(own.columns[1:], ["lang", "text"])]):
                    yield pa.RecordBatch.from_arrays([pa.array([part] * rows.num_rows, pa.int64()), rows.column(0), rows.column(1)], ["part", "lang", "g"])

    return make


def _answered(order: int, text: str):
    def make(key: tuple, rows: pa.Table, grams: pa.Table) -> pa.Table:
        known = {}
        for lang in set(grams["lang"].to_pylist()):
            own = grams.filter(pa.compute.equal(grams["lang"], lang)).combine_chunks()
            known[lang] = _table(own["g"].chunk(0), own["v"].to_numpy(), order)
        scores = []
        for t, lang in zip(rows[text].to_pylist(), rows["model_"].to_pylist(), strict=True):
            if not t or lang not in known:
                scores.append(None)
                continue
            hit, found = known[lang].get(codes(padded(symbols(t), order), order)[order])
            scores.append(float(np.exp(-found.mean())) if hit.all() and not np.isnan(found).any() else None)
        return rows.drop_columns(["part_", "model_"]).append_column("score", pa.array(scores, pa.float64()))

    return make


def scored_by_shards(rows: DataFrame, model: DataFrame, text: str, lang: str, order: int = ORDER) -> DataFrame:
    """As scored, with the tables joined to the distinct n-grams of each part of the rows, nothing broadcast."""
    langs = model.where("k = 0").select(F.col("lang").alias("known_")).distinct()
    named = rows.join(langs, F.col(lang).eqNullSafe(F.col("known_")), "left").withColumn("model_", F.coalesce("known_", F.lit(ANY))).drop("known_")
    parts = max(1, -(-rows.count() // PART_ROWS))
    dealt = staged(named.withColumn("part_", F.pmod(F.xxhash64(text, F.monotonically_increasing_id()), F.lit(parts))), "parts")
    asked = in_arrow(dealt.select(F.col("part_").alias("part"), F.col("model_").alias("lang"), text), _asked(order), "part long, lang string, g string").distinct()
    value: Column = F.col("v0")
    joined = asked.join(model.where("k = 0").select("lang", F.col("v").alias("v0")), "lang")
    for k in range(1, order + 1):
        p = model.where(f"k = {k} and kind = 'p'").select("lang", F.col("g").alias("g_"), F.col("v").alias(f"p{k}"))
        w = model.where(f"k = {k} and kind = 'w'").select(F.col("lang"), F.col("g").alias("h_"), F.col("v").alias(f"w{k}"))
        joined = joined.withColumn("g_", F.expr(f"right(g, {k})")).withColumn("h_", F.expr(f"left(right(g, {k}), {k - 1})"))
        joined = joined.join(shuffled(p), ["lang", "g_"], "left").join(shuffled(w), ["lang", "h_"], "left").drop("g_", "h_")
        value = F.coalesce(F.col(f"p{k}"), F.coalesce(F.col(f"w{k}"), F.lit(0.0)) + value)
    answers = joined.select(F.col("part").alias("part_"), "lang", "g", value.alias("v"))
    workers_see_package(rows.sparkSession)
    schema = T.StructType([*rows.schema.fields, T.StructField("score", T.DoubleType())])
    return dealt.groupBy("part_").cogroup(answers.groupBy("part_")).applyInArrow(_answered(order, text), schema)


def shared_tables(model: DataFrame, order: int = ORDER, largest: int = LARGEST) -> Broadcast | None:
    """The tables on every worker; None if they are too large. The driver keeps nothing of them."""
    if model.count() > largest:
        return None
    shared = model.sparkSession.sparkContext.broadcast(loaded(model, order, Packed))
    give_back()
    return shared


def scored(rows: DataFrame, model: DataFrame, shared: Broadcast | None, text: str = "text", lang: str = "lang", order: int = ORDER) -> DataFrame:
    """All columns and score, the perplexity per symbol (null for null and empty texts, and where no model is)."""
    if shared is None:
        return scored_by_shards(rows, model, text, lang, order)
    schema = T.StructType([*rows.schema.fields, T.StructField("score", T.DoubleType())])
    return in_arrow(rows, _scored(shared, rows.columns.index(text), rows.columns.index(lang)), schema)


def trusted_rows(docs: DataFrame, labels: DataFrame, id_col: str, text_col: str, lang_col: str) -> DataFrame:
    """lang, text of the documents that some label calls good."""
    good = labels.where("quality = 1").select(F.col("doc_id").alias("good_id")).distinct()
    if good.count() <= BROADCAST_IDS:
        good = F.broadcast(good)
    return docs.join(good, F.col(id_col) == F.col("good_id"), "left_semi").select(F.coalesce(F.col(lang_col), F.lit("")).alias("lang"), F.col(text_col).alias("text"))


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", quantile: float = QUANTILE, order: int = ORDER, largest: int = LARGEST) -> tuple[DataFrame, Broadcast | None, DataFrame]:
    """The staged tables, the same on every worker (or None), and (lang, limit). Where documents have languages without trusted ones, a further model, ANY, of all trusted documents is made for these."""
    trusted = trusted_rows(docs, labels, id_col, text_col, lang_col)
    langs = docs.select(F.coalesce(F.col(lang_col), F.lit("")).alias("lang")).distinct()
    if not langs.join(trusted.where("text <> ''").select("lang").distinct(), "lang", "left_anti").isEmpty():
        trusted = trusted.select(F.explode(F.array("lang", F.lit(ANY))).alias("lang"), "text")
    model = staged(tables(count_grams(trusted, order), order), "tables")
    shared = shared_tables(model, order, largest)
    scores = scored(trusted, model, shared, order=order).select("lang", "score")
    return model, shared, staged(scores.groupBy("lang").agg(F.percentile_approx("score", quantile, 10_000).alias("limit")), "limits")


def judged(rows: DataFrame, limits: DataFrame, lang: str) -> DataFrame:
    """Adds limit and kept to rows with score: kept if score is at most the limit of the language (or of ANY)."""
    few = limits.count() <= BROADCAST_LANGS
    named = lambda x: limits.where(F.col("lang") == ANY).agg(F.max("limit").alias("any_limit")) if x else limits.select(F.col("lang").alias("limit_lang"), F.col("limit").alias("own_limit"))
    own = F.broadcast(named(False)) if few else named(False)
    rows = rows.join(own, F.coalesce(F.col(lang), F.lit("")) == F.col("limit_lang"), "left").crossJoin(F.broadcast(named(True)))  # one row
    limit = F.coalesce("own_limit", "any_limit")
    return rows.withColumn("limit", limit).withColumn("kept", F.coalesce(F.col("score") <= F.col("limit"), F.lit(False))).drop("limit_lang", "own_limit", "any_limit")


def _judged_docs(docs: DataFrame, labels: DataFrame, id_col: str, text_col: str, lang_col: str, how: dict) -> DataFrame:
    """docs as c0, c1, .. with score, limit, kept."""
    model, shared, limits = fit(docs, labels, id_col, text_col, lang_col, **how)
    names = docs.columns
    inner = docs.select(*[F.col(f"`{c}`").alias(f"c{k}") for k, c in enumerate(names)])
    text, lang = f"c{names.index(text_col)}", "lang_"
    inner = inner.withColumn(lang, F.coalesce(f"c{names.index(lang_col)}", F.lit("")))
    return judged(scored(inner, model, shared, text, lang, how.get("order", ORDER)), limits, lang)


def classify(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", **how) -> DataFrame:
    """One row per input row: doc_id, lang, perplexity, limit, kept.

    Null and empty texts have no perplexity and aren't kept. A null language is the empty one. A language without
    trusted documents takes the model and limit of all of them; without any trusted
    document nothing has a limit and nothing is kept. Null ids are never trusted; of repeated ids every row is. Repeated rows get equal results.
    """
    names = docs.columns
    out = _judged_docs(docs, labels, id_col, text_col, lang_col, how)
    return out.select(F.col(f"c{names.index(id_col)}").alias("doc_id"), F.col(f"c{names.index(lang_col)}").alias("lang"), F.col("score").alias("perplexity"), "limit", "kept")


def keep_good(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", **how) -> DataFrame:
    """The rows of docs that classify keeps, with all their columns."""
    out = _judged_docs(docs, labels, id_col, text_col, lang_col, how).where("kept")
    return out.select(*[F.col(f"c{k}").alias(c) for k, c in enumerate(docs.columns)])
