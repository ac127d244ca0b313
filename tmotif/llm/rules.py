"""Quality rules: a threshold table compiled into one projection. Native: no user functions.

Repeated three-word windows are found by sorting a document's window hashes
with their places, so the cost is n log n for a text of n words.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tmotif.llm.common import SPACE_CLASS

#: Symbols counted by the contract, and the six ASCII white space characters.
SYMBOLS = "#*$%&|<>"
SPACES = " \t\n\x0b\x0c\r"
#: Frequent function words; a language without a list isn't judged by them.
STOP_WORDS = {
    "en": ("the", "of", "and", "to", "in", "is", "that", "it", "for", "was", "on", "with", "as", "be", "by", "at", "this", "are", "or", "an", "a"),
    "de": ("der", "die", "und", "in", "den", "von", "zu", "das", "mit", "ist", "nicht", "ein", "eine", "für", "auf"),
    "fr": ("de", "la", "le", "et", "les", "des", "un", "une", "du", "que", "est", "dans", "pour", "en"),
    "es": ("de", "la", "que", "el", "en", "y", "los", "se", "del", "las", "un", "por", "con", "no", "una"),
}
#: (measure, least, most); None: no limit. A measure that is null passes.
THRESHOLDS = (
    ("n_words", 50, None),
    ("repeat_share", None, 0.5),
    ("mean_word_length", 2.0, 16.0),
    ("symbol_ratio", None, 0.25),
    ("stop_word_ratio", 0.03, None),
    ("dup_line_ratio", None, 0.6),
)


def _is_one_of(words: tuple[str, ...]):
    """With at most one mark behind the word; the set is looked up by hash."""
    forms = [w + mark for w in words for mark in ("", *".,;:")]
    return lambda w: w.isin(*forms)


def measures(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str | None = "lang") -> DataFrame:
    """doc_id, lang, n_words, word_chars, n_symbols, n_lines, n_dup_lines, n_repeat_words, n_stop_words (null: language without a list)."""
    lang = F.col(lang_col) if lang_col and lang_col in docs.columns else F.lit(None).cast("string")
    rows = docs.select(F.col(id_col).alias("doc_id"), lang.alias("lang"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    has_word = F.length(F.translate("text", SPACES, "")) > 0
    words = F.when(has_word, F.split(F.regexp_replace("text", rf"^{SPACE_CLASS}|{SPACE_CLASS}$", ""), SPACE_CLASS)).otherwise(F.array().cast("array<string>"))
    lines = F.filter(F.split("text", "\n"), lambda x: F.length(F.translate(x, SPACES, "")) > 0)
    rows = rows.select("doc_id", "lang", "text", words.alias("words"), lines.alias("lines"))
    n = F.size("words")
    windows = F.when(n >= 3, F.transform(F.sequence(F.lit(0), n - 3), lambda i: F.xxhash64(F.get("words", i), F.get("words", i + 1), F.get("words", i + 2)))).otherwise(F.array().cast("array<bigint>"))
    stops = [F.when(F.col("lang") == k, F.size(F.filter("words", _is_one_of(v)))) for k, v in STOP_WORDS.items()]
    rows = rows.select(
        "doc_id",
        "lang",
        n.cast("long").alias("n_words"),
        F.length(F.translate("text", SPACES, "")).cast("long").alias("word_chars"),
        (F.length("text") - F.length(F.translate("text", SYMBOLS, ""))).cast("long").alias("n_symbols"),
        F.size("lines").cast("long").alias("n_lines"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        F.coalesce(*stops).cast("long").alias("n_stop_words"),
        windows.alias("windows"),
    )
    # one hash pass finds the texts that repeat nothing; only the others are sorted
    repeats = F.size(F.array_distinct("windows")) < F.size("windows")
    rows = rows.withColumn("windows", F.when(repeats, F.array_sort(F.transform("windows", lambda h, i: F.struct(h.alias("h"), i.alias("p"))))))
    return rows.select(*[c for c in rows.columns if c != "windows"], F.coalesce(covered(F.col("windows")), F.lit(0).cast("long")).alias("n_repeat_words"))


def covered(windows: Column) -> Column:
    """Words in windows whose hash stands twice or more in the sorted (hash, place) list."""
    last = F.size(windows) - 1
    same = F.transform(windows, lambda x, i: F.when(((i > 0) & (F.get(windows, i - 1)["h"] == x["h"])) | ((i < last) & (F.get(windows, i + 1)["h"] == x["h"])), x["p"]))
    places = F.array_sort(F.filter(same, lambda p: p.isNotNull()))
    start = F.struct(F.lit(0).alias("end"), F.lit(0).alias("n"))
    return F.aggregate(places, start, lambda acc, p: F.struct((p + 3).alias("end"), (acc["n"] + F.least(F.lit(3), p + 3 - acc["end"])).alias("n")), lambda acc: acc["n"].cast("long"))


def judged(rows: DataFrame, thresholds=THRESHOLDS) -> DataFrame:
    """Adds base_failed, failed (names of the rules that a row breaks) and kept."""
    words = F.greatest(F.col("n_words"), F.lit(1))
    value = {
        "n_words": F.col("n_words"),
        "repeat_share": F.col("n_repeat_words") / words,
        "mean_word_length": F.col("word_chars") / words,
        "symbol_ratio": F.col("n_symbols") / words,
        "stop_word_ratio": F.col("n_stop_words") / words,
        "dup_line_ratio": F.col("n_dup_lines") / F.greatest(F.col("n_lines"), F.lit(1)),
    }
    broken = []
    for name, least, most in thresholds:
        tests = [x for x in (value[name] < least if least is not None else None, value[name] > most if most is not None else None) if x is not None]
        for test in tests:
            broken.append(F.when(test, F.lit(name)))
    base = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    failed = F.array_compact(F.array(*broken))
    return rows.select("*", base.alias("base_failed"), failed.alias("failed"), (~base & (F.size(failed) == 0)).alias("kept"))


def quality_rules(docs: DataFrame, thresholds=THRESHOLDS, id_col: str = "doc_id", text_col: str = "text", lang_col: str | None = "lang") -> DataFrame:
    """One row per input row: doc_id, the measures, base_failed, failed, kept. A null text has no words and fails."""
    return judged(measures(docs, id_col, text_col, lang_col), thresholds)


def oracle() -> str:
    """The same over the table documents (unique ids), in another engine's SQL."""
    quoted = lambda xs: ", ".join(f"'{x}'" for x in xs)
    stops = " ".join(f"WHEN '{k}' THEN len(list_filter(w, lambda x: x IN ({quoted(a + mark for a in v for mark in ('', *'.,;:'))})))" for k, v in STOP_WORDS.items())
    value = {"n_words": "n", "repeat_share": "r / greatest(n, 1)", "mean_word_length": "c / greatest(n, 1)", "symbol_ratio": "s / greatest(n, 1)", "stop_word_ratio": "stops / greatest(n, 1)", "dup_line_ratio": "dups / greatest(n_lines, 1)"}
    tests = [f"coalesce({value[name]} {sign} {limit}, false)" for name, least, most in THRESHOLDS for sign, limit in (("<", least), (">", most)) if limit is not None]
    return rf"""
WITH d AS (
  SELECT doc_id, lang, coalesce(text, '') AS text, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents
), m AS (
  SELECT doc_id, w, len(w) AS n, coalesce(list_sum(list_transform(w, lambda x: length(x))), 0) AS c, length(regexp_replace(text, '[^{SYMBOLS}]', '', 'g')) AS s,
         list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS lines, CASE lang {stops} END AS stops FROM d
), windows AS (
  SELECT doc_id, i, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] AS k FROM m, unnest(range(1, n - 1)) t(i)
), twice AS (
  SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, k) AS times FROM windows) WHERE times > 1
), repeats AS (
  SELECT doc_id, count(DISTINCT p) AS r FROM twice, unnest([i, i + 1, i + 2]) u(p) GROUP BY doc_id
), v AS (
  SELECT doc_id, n, c, s, len(lines) AS n_lines, len(lines) - len(list_distinct(lines)) AS dups, stops, coalesce(r, 0) AS r FROM m LEFT JOIN repeats USING (doc_id)
)
SELECT doc_id, CAST(n AS BIGINT) AS n_words, CAST(c AS BIGINT) AS word_chars, CAST(s AS BIGINT) AS n_symbols, CAST(dups AS BIGINT) AS n_dup_lines, CAST(r AS BIGINT) AS n_repeat_words,
       (n < 50 OR 100 * r > 50 * n) AS base_failed, NOT (n < 50 OR 100 * r > 50 * n OR {" OR ".join(tests)}) AS kept
FROM v
"""
