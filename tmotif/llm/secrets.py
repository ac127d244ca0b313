"""Secret scans with a random forest that removes false positives. Native: DataFrame functions only.

A pattern finds candidates: private key blocks from BEGIN to END, values that a secret word
names, and long runs of key characters with a digit. Each is described by length, character transitions, dictionary
coverage, path signs and the words beside it. A forest of small trees, grown on labelled findings,
is compiled into one expression over these features; candidates that half of
the trees or more call secret are reported and can be redacted.
"""

from __future__ import annotations

import random

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: From BEGIN to END; without an END the header and the lines of key characters that follow it.
KEY_BLOCK = r"-----BEGIN [A-Z0-9 ]*PRIVATE KEY(?: BLOCK)?-----(?:[^-]*+(?:-{1,4}+[^-]++){0,200}+-----END [A-Z0-9 ]*PRIVATE KEY(?: BLOCK)?-----|(?:[\x20\x09-\x0D]+[A-Za-z0-9+/=]{16,}+){0,1000}+)"
#: Values of 6 characters or more after a secret word and = or : (the first, short look behind is for speed).
NAMED = r"""(?<=[=:]>?[\x20\t]{0,2}["']?)(?<=(?i:token|secret|passw|api[_-]?key|access[_-]?key|auth|credential|private|pwd)[A-Za-z0-9_-]{0,16}["']?[\x20\t]{0,2}[=:]{1,2}>?[\x20\t]{0,2}["']?)[^\x20\x09-\x0D"'<>,;()\[\]{}=:][^\x20\x09-\x0D"'<>,;()\[\]{}]{4,}[^\x20\x09-\x0D"'<>,;()\[\]{}.:!?]"""
#: Runs of 16 characters or more with a digit among them, as whole words; = only ends one, so that a name before it stays in the left context.
RUN = r"(?<![A-Za-z0-9+/_.~-])(?=[A-Za-z+/_.~-]*[0-9])[A-Za-z0-9+/_.~-]{16,}={0,2}"
CANDIDATE = f"{KEY_BLOCK}|{NAMED}|{RUN}"
BESIDE = 32
#: Word parts that readable names are made of.
DICTIONARY = r"(?i)the|and|ing|ion|tion|test|user|file|http|www|com|html|index|page|name|image|data|version|build|release|config|module|class|node|lib|src|main|table|report|year|month"
SECRET_WORD = r"(?i)token|secret|passw|api[_-]?key|apikey|access[_-]?key|auth|credential|private|pwd"
HARMLESS_WORD = r"(?i)commit|sha-?\d|sha\b|md5|checksum|digest|hash|uuid|guid|revision|etag|isbn|order|card|phone|page"
KINDS = (("cloud_key", r"^AKIA[0-9A-Z]{16}$"), ("forge_token", r"^gh[pousr]_[A-Za-z0-9]{30,}$"), ("chat_token", r"^xox[baprs]-"), ("web_token", r"^eyJ[A-Za-z0-9_-]+\.[A-Za-z0-9_.-]+$"), ("private_key", r"^-----BEGIN"))
FEATURES = ("length", "transitions", "dictionary", "path", "secret_word", "harmless_word", "digits", "distinct", "known", "mixed")
TREES, DEPTH, SEED = 15, 4, 7
#: Labelled findings that the forest is grown on, at most.
MOST_FINDINGS = 2000


def features(text: Column, left: Column, right: Column, words: str = DICTIONARY) -> dict[str, Column]:
    """words: the dictionary as a regular expression."""
    size = F.greatest(F.length(text), F.lit(1))
    known = F.lit(False)
    for _, pattern in KINDS:
        known = known | text.rlike(pattern)
    number = lambda x: x.cast("double")
    return {
        "length": number(F.length(text)),
        "transitions": number(F.regexp_count(text, F.lit("[a-z](?=[A-Z0-9])|[A-Z](?=[a-z0-9])|[0-9](?=[A-Za-z])"))) / size,
        "dictionary": number(F.length(text) - F.length(F.regexp_replace(text, words, ""))) / size,
        "path": number(text.rlike(r"^[./~]|/.*/|\.[a-z]{2,4}$|^www") | left.rlike(r"[/\\@:]$") | right.rlike(r"^[/\\@]")),
        "secret_word": number(left.rlike(SECRET_WORD)),
        "harmless_word": number(left.rlike(HARMLESS_WORD)),
        "digits": number(F.regexp_count(text, F.lit("[0-9]"))) / size,
        "distinct": number(F.size(F.array_distinct(F.split(text, "")))) / size,
        "known": number(known),
        "mixed": number(text.rlike("[a-z]")) + number(text.rlike("[A-Z]")) + number(text.rlike("[0-9]")),
    }


def labelled_findings(n: int = 480, seed: int = SEED) -> list[tuple[str, str, str, int]]:
    """(left, candidate, right, 1 if secret) made by rule: the labels that the forest is grown on by default."""
    rnd = random.Random(seed)
    pick = lambda letters, k: "".join(rnd.choice(letters) for _ in range(k))
    low, up, num = "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789"
    hexa, base = "0123456789abcdef", low + up + num
    words = ["index", "report", "image", "module", "version", "release", "config", "table", "data", "page"]
    out = []
    for k in range(n):
        around = rnd.choice(["the ", "see ", "and then ", "in the ", "with "])
        if k % 2:
            word = rnd.choice(['token = "', "secret: ", "api_key=", 'password = "', "auth ", "access_key: ", "TOKEN = ", 'credential "'])
            kind = rnd.randrange(7)
            text = ("AKIA" + pick(up + num, 16), "ghp_" + pick(base, 36), "xoxb-" + pick(num, 12) + "-" + pick(base, 24), "eyJ" + pick(base, 20) + "." + pick(base, 40), pick(hexa, 40), pick(base + "+/", 40), pick(hexa, 32).upper())[kind]
            left = around + (word if kind > 3 or rnd.random() < 0.6 else "")
            out.append((left[-BESIDE:], text, rnd.choice(['"', " ", '" and', "\n"]), 1))
        else:
            kind = rnd.randrange(7)
            text = (pick(hexa, 40), pick(hexa, 8) + "-" + "-".join(pick(hexa, 4) for _ in range(3)) + "-" + pick(hexa, 12), pick(num, 16), "/".join(rnd.choice(words) for _ in range(4)) + f"/{pick(num, 3)}.html", "-".join(rnd.choice(words) for _ in range(3)) + f"-{pick(num, 4)}", "".join(rnd.choice(words) for _ in range(3)) + pick(num, 2), pick(hexa, 32))[kind]
            harmless = {0: ["commit ", "revision ", "sha1 "], 1: ["uuid ", "id ", "guid "], 2: ["card ", "order ", ""], 6: ["md5 ", "checksum: ", "etag "]}.get(kind, ["", "at http://", "file "])
            out.append(((around + rnd.choice(harmless))[-BESIDE:], text, rnd.choice([" ", ".", "\n", " in"]), 0))
    return out


def named_findings(n: int = 320, seed: int = SEED) -> list[tuple[str, str, str, int]]:
    """More labels made by rule: key blocks and short values that a secret word names, and plain words there."""
    rnd = random.Random(seed)
    pick = lambda letters, k: "".join(rnd.choice(letters) for _ in range(k))
    low, up, num = "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789"
    syllables = ["cor", "rect", "hor", "se", "bat", "ter", "sta", "ple", "hun", "mon", "key", "dra", "gon", "sun", "shi", "ne", "pass", "blue"]
    word = lambda k: "".join(rnd.choice(syllables) for _ in range(k))
    plain = ["required", "invalid", "please", "missing", "unknown", "expired", "optional", "string", "changed", "forgotten", "something", "generated", "authentication"]
    out = []
    for k in range(n):
        name = rnd.choice(['password = "', "password: ", "secret=", "pwd: ", 'api_key: "', "TOKEN=", "auth_token = ", "PASSWORD="])
        left, right = rnd.choice(["the ", "see ", "", "with "]) + name, rnd.choice(['"', " ", "\n", ""])
        kind = k % 8
        if kind == 0:
            label = rnd.choice(["RSA ", "EC ", "", "OPENSSH "])
            lines = "\n".join(pick(low + up + num + "+/", 64) for _ in range(rnd.randint(1, 26)))
            head, end = f"-----BEGIN {label}PRIVATE KEY-----", f"\n-----END {label}PRIVATE KEY-----"
            out.append((rnd.choice(["", "key:\n", "see "]), (head + "\n" + lines + end, head + "\n" + lines, head)[k // 8 % 3], rnd.choice(["\n", " "]), 1))
        elif kind in (1, 2):
            out.append((left[-BESIDE:], "".join(w.capitalize() if i else w for i, w in enumerate(word(rnd.randint(1, 2)) for _ in range(rnd.randint(2, 4)))), right, 1))
        elif kind == 3:
            out.append((left[-BESIDE:], word(rnd.randint(1, 3)) + pick(num, rnd.randint(1, 4)) + word(rnd.randint(0, 2)), right, 1))
        elif kind == 4:
            out.append((left[-BESIDE:], pick(low + up + num + "!@#%&*", rnd.randint(8, 20)), right, 1))
        else:
            out.append((left[-BESIDE:], rnd.choice(plain) if kind < 7 else "http://www." + word(2) + ".com/" + rnd.choice(plain), right, 0))
    return out


def findings_table(spark: SparkSession, findings: list[tuple[str, str, str, int]]) -> DataFrame:
    rows = [F.struct(F.lit(a).alias("left"), F.lit(b).alias("candidate"), F.lit(c).alias("right"), F.lit(d).alias("label")) for a, b, c, d in findings]
    return spark.range(1).select(F.inline(F.array(*rows)))


def learned_words(docs: DataFrame, most: int = 200, text_col: str = "text") -> list[str]:
    """The words of 4 to 12 letters that most documents hold, in that order, at most so many: a dictionary of the texts at hand."""
    words = F.array_distinct(F.regexp_extract_all(F.lower(F.coalesce(F.col(text_col), F.lit(""))), F.lit("(?<![a-z])[a-z]{4,12}(?![a-z])"), F.lit(0)))
    counts = docs.select(F.explode(words).alias("word")).groupBy("word").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    return [r["word"] for r in counts.orderBy(F.desc("n"), "word").limit(most).collect()]


def dictionary_of(words: list[str]) -> str:
    """The fixed word parts and these words, longest first, as a regular expression."""
    own = sorted({*words, *DICTIONARY.removeprefix("(?i)").split("|")}, key=lambda w: (-len(w), w))
    return "(?i)" + "|".join(own)


def table_findings(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, left, candidate, right, label: candidates of the documents that rules label for sure.

    1: of a known kind, or 16 characters or more named by a secret word. 0: a host name, a number, an address, a file, a value
    after a harmless word. All others are left out.
    """
    between, texts = F.split("text", CANDIDATE), F.regexp_extract_all("text", F.lit(CANDIDATE), F.lit(0))
    rows = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text")).withColumn("found", texts)
    rows = rows.where(F.size("found") > 0).withColumn("between", between).select("doc_id", "between", F.posexplode("found").alias("i", "candidate"))
    rows = rows.select("doc_id", F.right(F.get("between", F.col("i")), F.lit(BESIDE)).alias("left"), "candidate", F.left(F.get("between", F.col("i") + 1), F.lit(BESIDE)).alias("right"))
    known = F.lit(False)
    for _, pattern in KINDS:
        known = known | F.col("candidate").rlike(pattern)
    harmless = F.col("candidate").rlike(r"^[a-z0-9-]+(\.[a-z0-9-]+)+$|^[0-9]+$|^[./~]|/.*/|\.[a-z]{2,4}$") | F.col("left").rlike(HARMLESS_WORD + "[^a-z]*$") | F.col("left").rlike("@$") | F.col("right").rlike("^@")
    named = F.col("left").rlike(SECRET_WORD + r"""["']?\s*[=:]+\s*["']?$""") & (F.length("candidate") >= 16)
    label = F.when(known | (named & ~harmless), 1).when(harmless & ~known, 0)
    return rows.withColumn("label", label).where("label is not null")


def _tree(x: np.ndarray, y: np.ndarray, rng: np.random.Generator, depth: int):
    """A leaf is a share of secrets, a node (feature, limit, at most, more)."""
    share = float(y.mean())
    if not depth or share in (0.0, 1.0) or len(y) < 6:
        return round(share, 4)
    best = None
    for f in rng.choice(x.shape[1], 4, replace=False):
        values = np.unique(x[:, f])
        for limit in (values[:-1] + values[1:]) / 2 if len(values) <= 24 else np.quantile(values, np.linspace(0.05, 0.95, 19)):
            left = x[:, f] <= limit
            if 0 < (k := left.sum()) < len(y):
                a, b = y[left].mean(), y[~left].mean()
                impurity = k * a * (1 - a) + (len(y) - k) * b * (1 - b)
                if best is None or impurity < best[0] - 1e-12:
                    best = impurity, int(f), float(round(limit, 6)), left
    if best is None:
        return round(share, 4)
    _, f, limit, left = best
    return f, limit, _tree(x[left], y[left], rng, depth - 1), _tree(x[~left], y[~left], rng, depth - 1)


def grow(labelled: DataFrame, trees: int = TREES, depth: int = DEPTH, seed: int = SEED, words: str = DICTIONARY) -> list:
    """A forest from rows (left, candidate, right, label); the first MOST_FINDINGS by hash if there are more. Scans must use the same words."""
    named = features(F.col("candidate"), F.col("left"), F.col("right"), words)
    rows = labelled.orderBy(F.xxhash64("left", "candidate", "right")).limit(MOST_FINDINGS).select(*[named[f].alias(f) for f in FEATURES], "label").collect()
    if not rows:
        raise ValueError("a forest needs labelled findings")
    x, y = np.array([r[:-1] for r in rows], float), np.array([r[-1] for r in rows], float)
    rng = np.random.default_rng(seed)
    forest = []
    for _ in range(trees):
        at = rng.integers(0, len(y), len(y))
        forest.append(_tree(x[at], y[at], rng, depth))
    return forest


def vote(forest: list, named: dict[str, Column]) -> Column:
    def leaf(node) -> Column:
        if not isinstance(node, tuple):
            return F.lit(node)
        f, limit, a, b = node
        return F.when(named[FEATURES[f]] <= limit, leaf(a)).otherwise(leaf(b))

    total = leaf(forest[0])
    for tree in forest[1:]:
        total = total + leaf(tree)
    return total / len(forest)


_FORESTS: dict[int, list] = {}


def default_forest(spark: SparkSession) -> list:
    if not _FORESTS:
        _FORESTS[0] = grow(findings_table(spark, labelled_findings() + named_findings()))
    return _FORESTS[0]


def candidates(text: Column) -> tuple[Column, Column]:
    """Candidates of a text, and the pieces between them."""
    return F.regexp_extract_all(text, F.lit(CANDIDATE), F.lit(0)), F.split(text, CANDIDATE)


def found(docs: DataFrame, forest: list, threshold: float = 0.5, words: str = DICTIONARY) -> DataFrame:
    """Adds findings to rows with column text: array of (start, length, kind, score), secret (whole texts of those at the threshold)."""
    found_texts, between = candidates(F.col("text"))
    rows = docs.withColumn("found", found_texts)
    rows = rows.withColumn("between", F.when(F.size("found") > 0, between))
    starts = F.transform(F.sequence(F.lit(1), F.size("found")), lambda n: F.aggregate(F.slice("between", F.lit(1), n), F.lit(0), lambda a, x: a + F.length(x)) + F.aggregate(F.slice("found", F.lit(1), n - 1), F.lit(0), lambda a, x: a + F.length(x)))
    rows = rows.withColumn("starts", F.when(F.size("found") > 0, starts))

    def described(c: Column, i: Column) -> Column:
        named = features(c, F.right(F.get("between", i), F.lit(BESIDE)), F.left(F.get("between", i + 1), F.lit(BESIDE)), words)
        return F.struct(c.alias("text"), F.get("starts", i).alias("start"), *[named[f].alias(f) for f in FEATURES])

    rows = rows.withColumn("described", F.when(F.size("found") > 0, F.transform("found", described)))

    def scored(d: Column) -> Column:
        kind = F.lit("generic")
        for name, pattern in reversed(KINDS):
            kind = F.when(d["text"].rlike(pattern), name).otherwise(kind)
        return F.struct(d["start"].alias("start"), F.length(d["text"]).alias("length"), kind.alias("kind"), vote(forest, {f: d[f] for f in FEATURES}).alias("score"), d["text"].alias("text"))

    rows = rows.withColumn("scored", F.when(F.size("found") > 0, F.transform("described", scored)))
    return rows.withColumn("secrets", F.coalesce(F.filter("scored", lambda s: s["score"] >= threshold), F.array().cast("array<struct<start:int,length:int,kind:string,score:double,text:string>>"))).withColumn("n_candidates", F.size("found").cast("long")).drop("found", "between", "starts", "described", "scored")


def redacted(text: Column, secrets: Column) -> Column:
    """The text with [kind] in place of each secret, by place."""
    start = F.struct(F.lit(1).alias("at"), F.lit("").alias("out"))
    cut = F.aggregate(secrets, start, lambda a, s: F.struct((s["start"] + s["length"] + 1).alias("at"), F.concat(a["out"], F.substring(text, a["at"], s["start"] + 1 - a["at"]), F.lit("["), s["kind"], F.lit("]")).alias("out")), lambda a: F.concat(a["out"], F.substring(text, a["at"], F.length(text))))
    return F.when(F.size(secrets) > 0, cut).otherwise(text)


def scan(docs: DataFrame, forest: list | None = None, id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.5, words: str = DICTIONARY) -> DataFrame:
    """One row per input row: doc_id, n_candidates, secrets (start, length, kind, score, text), redacted.

    A null text has none and is redacted to null, an empty one to the empty text. Rows are scanned one by one: null ids and
    repeated rows stay as they are; other columns are not looked at. words: the dictionary the forest was grown with.
    """
    forest = forest or default_forest(docs.sparkSession)
    rows = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"), F.col(text_col).isNull().alias("none"))
    rows = found(rows, forest, threshold, words)
    return rows.select("doc_id", "n_candidates", "secrets", F.when(~F.col("none"), redacted(F.col("text"), F.col("secrets"))).alias("redacted"))


def redact(docs: DataFrame, forest: list | None = None, text_col: str = "text", threshold: float = 0.5) -> DataFrame:
    """docs with secrets replaced in the text; all rows and columns stay."""
    names = docs.columns
    forest = forest or default_forest(docs.sparkSession)
    rows = docs.select(*[F.col(f"`{c}`").alias(f"c{k}") for k, c in enumerate(names)])
    at = names.index(text_col)
    rows = found(rows.withColumn("text", F.coalesce(F.col(f"c{at}"), F.lit(""))), forest, threshold)
    return rows.select(*[(F.when(F.col(f"c{k}").isNotNull(), redacted(F.col("text"), F.col("secrets"))) if k == at else F.col(f"c{k}")).alias(c) for k, c in enumerate(names)])
