"""URL pattern rules: several hundred through the index against a scan of all."""

import random
import re

import pytest

from tmotif.llm import urls


def scan(url: str | None, rules) -> tuple[str | None, str]:
    """Every rule tried, by a matcher of its own."""
    rest = url.split("://", 1)[1] if url and "://" in url else ""
    host = re.match(r"[^/?#]*", rest)[0]
    path = re.match(r"[^?#]*", rest[len(host) :])[0]
    host = host.lower()

    def fits(pattern: str, text: str, stop: str) -> set[int]:
        """Ends of the matches of a pattern at the start of a text."""
        ends = {0}
        for part in re.findall(r"\[[^\]]*\]|.", pattern, re.S):
            if part == "*":
                ends = {k for e in ends for k in range(e, len(text) + 1) if not set(text[e:k]) & set(stop)}
            elif len(part) > 1:
                ends = {e + 1 for e in ends if e < len(text) and text[e] not in stop and re.fullmatch(part, text[e])}
            else:
                ends = {e + 1 for e in ends if text[e : e + 1] == part}
        return ends

    found = []
    for verdict, h, p in rules:
        tails = [host] + [host[k + 1 :] for k, c in enumerate(host) if c == "."]
        if any(len(t) in fits(h.lower(), t, "./") for t in tails) and fits(p, path, ""):
            found.append((len(h) + len(p), verdict == "block", h + p, verdict))
    return max(found)[2:] if found else (None, urls.DEFAULT)


@pytest.mark.parametrize("n", [40, 400])
def test_patterns_against_a_scan(spark, n):
    rnd = random.Random(n)
    label = lambda: rnd.choice(["a", "ads", "x1", "cdn", "shop", "media", f"h{rnd.randrange(40)}"])
    wild = lambda: rnd.choice(["*", "ad*", "[a-c]x", "h[0-9]", "*s", "[^a]*"])
    part = lambda loose: wild() if rnd.random() < loose else label()
    rules = [*urls.RULES]
    while len(rules) < n:
        host = ".".join([part(0.3) for _ in range(rnd.randint(0, 2))] + [rnd.choice(["com", "net", "test", "*"])])
        path = "/" + "/".join(part(0.3) for _ in range(rnd.randint(0, 3))) + rnd.choice(["", "/", "/*.html"])
        rules.append((rnd.choice(["block", "allow"]), host, path))
    assert any(not urls.rule_tokens(h, p) for _, h, p in rules)
    pages = [(None, None, "x"), (1, "", "x"), (2, "no scheme", "x"), (2, "no scheme", "x")]
    for k in range(500):
        host = ".".join([label() if rnd.random() < 0.8 else rnd.choice(["ax", "bx", "adsy", "SHOPS"]) for _ in range(rnd.randint(0, 3))] + [rnd.choice(["com", "net", "test", "org"])])
        path = "/" + "/".join(label() for _ in range(rnd.randint(0, 4))) + rnd.choice(["", "/", "/i.html", "?q=/a/", "#/x"])
        pages.append((k, f"http://{host}{path}", "x"))
    df = spark.createDataFrame(pages, "page_id bigint, url string, rule string")
    got = sorted(map(repr, ((r["page_id"], r["rule"], r["verdict"]) for r in urls.filter_urls(df, rules).collect())))
    assert got == sorted(map(repr, ((i, *scan(u, rules)) for i, u, _ in pages)))
    assert len({x for x in got}) > 100


def test_only_fetched_rules_run():
    index = urls.compiled([("block", "a.com", "/x/y/"), ("allow", "b.com", "/x/"), ("block", "*.com", "/*"), ("block", "*", "/q[0-9]")])
    assert [t for t, *_ in index] == [".a", ".b", ".com", "*"]
