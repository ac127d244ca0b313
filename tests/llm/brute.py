"""Brute-force versions of the contracts, for small tables."""

from __future__ import annotations

import hashlib
import re
import zlib

import numpy as np
import xxhash

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SPACE = re.compile(r"[\x20\x09-\x0D]+")


def fingerprint(text: str | None, width: int = 3) -> int:
    lower = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    words = WORD.findall(lower)
    if not words:
        return 0
    shingles = [" ".join(words[i : i + width]) for i in range(len(words) - width + 1)] or [" ".join(words)]
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def components(nodes: list, linked) -> dict:
    """node -> smallest node reachable; linked(a, b) over all pairs."""
    parent = {n: n for n in nodes}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, a in enumerate(nodes):
        for b in nodes[:i]:
            if root(a) != root(b) and linked(a, b):
                ra, rb = root(a), root(b)
                parent[max(ra, rb)] = min(ra, rb)
    return {n: root(n) for n in nodes}


def simhash_components(texts: dict[int, str | None], width: int = 3, bits: int = 2) -> dict[int, tuple[str, int]]:
    prints = {d: fingerprint(t, width) for d, t in texts.items()}
    distinct = np.array(sorted(set(prints.values())), np.uint64)
    parent = {int(x): int(x) for x in distinct}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for x in distinct:
        near = distinct[np.bitwise_count(distinct ^ x) <= bits]
        for y in near:
            a, b = root(int(x)), root(int(y))
            parent[max(a, b)] = min(a, b)
    low: dict[int, int] = {}
    for d, p in prints.items():
        r = root(p)
        low[r] = min(low.get(r, d), d)
    return {d: (f"{p:016x}", low[root(p)]) for d, p in prints.items()}


def exact(texts: dict[int, str | None]) -> dict[int, tuple[int, int, bool, str]]:
    groups: dict[str, list[int]] = {}
    for d, t in texts.items():
        groups.setdefault(SPACE.sub(" ", t or ""), []).append(d)
    return {d: (min(g), len(g), d == min(g), hashlib.sha256(t.encode()).hexdigest()) for t, g in groups.items() for d in g}


def rules(text: str | None) -> tuple[int, int, int, int, int, bool]:
    text = text or ""
    words = WORD.findall(text)
    lines = [x for x in text.split("\n") if WORD.search(x)]
    places: dict[tuple, list[int]] = {}
    for i in range(len(words) - 2):
        places.setdefault(tuple(words[i : i + 3]), []).append(i)
    covered = {i + k for p in places.values() if len(p) > 1 for i in p for k in range(3)}
    n = len(words)
    return n, sum(map(len, words)), sum(c in "#*$%&|<>" for c in text), len(lines) - len(set(lines)), len(covered), n < 50 or 100 * len(covered) > 50 * n


def crc(ids: list[int]) -> int:
    return zlib.crc32(np.array(ids, "<u4").tobytes())


def url(u: str | None) -> tuple[str, str, str | None, str]:
    rest = u.split("://", 1)[1] if u and "://" in u else ""
    host = re.match(r"[^/?#]*", rest)[0]
    path = re.match(r"[^?#]*", rest[len(host) :])[0]
    host = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in host)
    fits = [(len(h + p), h + p, v) for v, h, p in (("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/")) if (host == h or host.endswith("." + h)) and path.startswith(p)]
    return host, path, max(fits)[1] if fits else None, max(fits)[2] if fits else "allow"
