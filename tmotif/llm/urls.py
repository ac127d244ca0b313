"""URL filters: rules indexed by their rarest literal token; a URL's tokens fetch the rules whose regular expressions run.

Native: DataFrame functions only. A rule is (verdict, host, path), both patterns: * stands for any characters
(in a host for any within a label), [...] for one character of a class, all else for itself. It fits
its host and all subdomains where the URL's path starts with its path.
"""

from __future__ import annotations

import re
from collections import Counter

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: The rules of the contract.
RULES = (("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/"))
#: Verdict where no rule fits.
DEFAULT = "allow"
#: More rules than this go through a join in place of a literal map.
LITERAL_RULES = 64
#: Rules come as a list of the driver; so many are broadcast at most, in any one call.
MOST_RULES = 1_000_000
#: What stands for other characters in a pattern: any run, or a class.
WILD = re.compile(r"\*|\[\^?[A-Za-z0-9._~%=&-]+\]")
#: Fetched by every URL: the index token of rules without a literal one.
ALWAYS = "*"


def rule_tokens(host: str, path: str) -> list[str]:
    """Host labels, marked by a dot, and whole path segments (a last one that is cut may be part of a longer one), where these are literal."""
    labels = [f".{x}" for x in host.lower().split(".") if x]
    return [t for t in labels + [f"/{x}" for x in path.split("/")[1:-1] if x] if not WILD.search(t)]


def expression(pattern: str, anything: str, before_class: str = "") -> str:
    """The regular expression of a pattern."""
    out, at = "", 0
    for m in WILD.finditer(pattern):
        out += re.escape(pattern[at : m.start()]) + (anything if m[0] == "*" else before_class + m[0])
        at = m.end()
    return out + re.escape(pattern[at:])


def compiled(rules=RULES) -> list[tuple[str, str, str, str, int]]:
    """(index token, rule text, regular expression, verdict, length): the literal token that the fewest rules have, the longest of these."""
    if len(rules) > MOST_RULES:
        raise ValueError(f"{len(rules)} rules are over the checked size {MOST_RULES}")
    seen = Counter(t for _, host, path in rules for t in set(rule_tokens(host, path)))
    out = []
    for verdict, host, path in rules:
        token = min(rule_tokens(host, path), key=lambda t: (seen[t], -len(t), t), default=ALWAYS)
        out.append((token, f"{host}{path}", f"(?s)^(?:[^/]*\\.)?{expression(host.lower(), '[^./]*', '(?![./])')}(?=/|$){expression(path, '.*')}", verdict, len(host) + len(path)))
    return out


def url_parts(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path; both empty for null or without '://'."""
    full = F.coalesce(url, F.lit(""))
    rest = F.when(F.instr(full, "://") > 0, F.regexp_extract(full, r"(?s)^.*?://(.*)$", 1)).otherwise("")
    host = F.regexp_extract(rest, r"^([^/?#]*)", 1)
    path = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    return F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), path


def _tokens(host: Column, path: Column) -> Column:
    labels = F.transform(F.split(host, r"\."), lambda x: F.concat(F.lit("."), x))
    return F.array_distinct(F.concat(F.array(F.lit(ALWAYS)), labels, F.transform(F.split(path, "/"), lambda x: F.concat(F.lit("/"), x))))


def _rule(rule: tuple) -> Column:
    _, text, pattern, verdict, length = rule
    return F.struct(F.lit(length).alias("length"), F.lit(verdict == "block").alias("block"), F.lit(text).alias("rule"), F.lit(pattern).alias("pattern"), F.lit(verdict).alias("verdict"))


def filter_urls(pages: DataFrame, rules=RULES, id_col: str = "page_id", url_col: str = "url", default: str = DEFAULT) -> DataFrame:
    """One row per input row: page_id, host, path, rule (null if none fits), verdict.

    The longest rule that fits wins, of equal lengths one that blocks, of these the last by text. Null, empty and scheme-less URLs have
    an empty host and path; where no rule fits these they get the default. Rows are judged one by one:
    null ids and repeated rows stay as they are, and other columns are not looked at.
    """
    index = compiled(rules)
    host, path = url_parts(F.col(url_col))
    rows = pages.select(F.col(id_col).alias("page_id"), host.alias("host"), path.alias("path"))
    whole = F.concat("host", "path")
    if len(index) <= LITERAL_RULES:
        by: dict[str, list] = {}
        for r in index:
            by.setdefault(r[0], []).append(_rule(r))
        fetch = F.create_map(*[x for t, rs in by.items() for x in (F.lit(t), F.array(*rs))])
        rows = rows.withColumn("tokens", _tokens(F.col("host"), F.col("path")))
        rows = rows.withColumn("fetched", F.flatten(F.transform(F.filter("tokens", lambda t: t.isin(*by)), lambda t: F.element_at(fetch, t))))
        rows = rows.withColumn("best", F.array_max(F.filter("fetched", lambda r: F.regexp_like(whole, r["pattern"]))))
    else:
        # each (host, path) is judged once, so that no row needs a number
        kinds = "token string, length int, block boolean, rule string, pattern string, verdict string"
        table = pages.sparkSession.createDataFrame([(t, n, v == "block", text, pattern, v) for t, text, pattern, v, n in index], kinds).select("token", F.struct("length", "block", "rule", "pattern", "verdict").alias("r"))
        asked = rows.select("host", "path").distinct().select("host", "path", F.explode(_tokens(F.col("host"), F.col("path"))).alias("token"))
        hit = asked.join(F.broadcast(table), "token").where(F.regexp_like(whole, F.col("r.pattern")))
        rows = rows.join(hit.groupBy("host", "path").agg(F.max("r").alias("best")), ["host", "path"], "left")
    return rows.select("page_id", "host", "path", F.col("best.rule").alias("rule"), F.coalesce("best.verdict", F.lit(default)).alias("verdict"))


ORACLE = r"""
WITH p AS (
  SELECT page_id, CASE WHEN url IS NOT NULL AND position('://' IN url) > 0 THEN substr(url, position('://' IN url) + 3) ELSE '' END AS rest FROM pages
), h AS (
  SELECT page_id, translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM p
), r(verdict, rhost, rpath) AS (VALUES ('block', 'net', '/'), ('allow', 'example.net', '/en/'), ('block', 'example.com', '/de/'), ('allow', 'org', '/fr/')),
f AS (
  SELECT h.page_id, h.host, h.path, r.rhost || r.rpath AS rule, r.verdict,
         row_number() OVER (PARTITION BY h.page_id, h.host, h.path ORDER BY length(r.rhost || r.rpath) DESC) AS k
  FROM h JOIN r ON (h.host = r.rhost OR ends_with(h.host, '.' || r.rhost)) AND starts_with(h.path, r.rpath)
)
SELECT h.page_id, h.host, h.path, f.rule, coalesce(f.verdict, 'allow') AS verdict
FROM h LEFT JOIN f ON h.page_id = f.page_id AND h.host = f.host AND h.path = f.path AND f.k = 1
"""
