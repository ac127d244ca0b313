"""Motifs, their anchors and the classes of anchors. Driver side only; nothing here touches data."""

from __future__ import annotations

from dataclasses import dataclass
from itertools import product


class AnchorError(ValueError):
    """The motif has no path or wedge that a sampler could start from."""


@dataclass(frozen=True)
class PathClass:
    """Class of a 3-path around a center (u, v): signs of the ends at u and v, and their sides in time.

    '-' is an in-edge, '+' an out-edge of the end vertex; '<' before the center, '>' after it.
    """

    a1: str
    a3: str
    b1: str
    b3: str

    @classmethod
    def all(cls) -> list[PathClass]:
        return [cls(*x) for x in product("-+", "-+", "<>", "<>")]

    def __str__(self) -> str:
        return f"{self.a1}{self.a3}{self.b1}{self.b3}"


@dataclass(frozen=True)
class WedgeClass:
    """Class of a wedge: the base edge's end that the other edge meets ('src' or 'dst'), its sign there, its side in time."""

    pivot: str
    a: str
    b: str

    @classmethod
    def all(cls) -> list[WedgeClass]:
        return [cls(*x) for x in product(("src", "dst"), "-+", "<>")]

    def __str__(self) -> str:
        return f"{self.pivot}{self.a}{self.b}"


@dataclass(frozen=True)
class Anchor:
    """Positions (end at the center's source, center, end at its target), or (base, other) of a wedge; and its vertices.

    vertices: of a path v0, v1, v2, v3 along it (v1 -> v2 is the center); of a
    wedge the base's source and target, then the third.
    """

    positions: tuple[int, ...]
    cls: PathClass | WedgeClass
    vertices: tuple[str, ...]

    @property
    def center(self) -> int:
        return self.positions[1] if len(self.positions) == 3 else self.positions[0]


@dataclass(frozen=True)
class Motif:
    """A pattern: directed edges between named vertices, listed in time order; parallel edges are allowed."""

    edges: tuple[tuple[str, str], ...]
    name: str = ""

    def __post_init__(self):
        if not self.edges:
            raise ValueError("a motif has at least one edge")
        if any(a == b for a, b in self.edges):
            raise ValueError("a motif has no loops")
        if not 3 <= len(self.vertices) <= 4:
            raise ValueError("a motif has three or four vertices")
        reached = {self.edges[0][0]}
        while more := {x for e in self.edges if set(e) & reached for x in e} - reached:
            reached |= more
        if reached != set(self.vertices):
            raise ValueError("a motif is connected")

    @classmethod
    def parse(cls, text: str, name: str = "") -> Motif:
        """From 'A>B, B>C, ...' or 'AB BC ...'."""
        parts = [p.strip() for p in text.replace(",", " ").split()]
        return cls(tuple(tuple(p.split(">")) if ">" in p else (p[0], p[1]) for p in parts), name)

    @property
    def vertices(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(x for e in self.edges for x in e))

    @property
    def free_edges(self) -> int:
        """r of the error bound: edges - vertices + 1."""
        return len(self.edges) - len(self.vertices) + 1

    def reversed(self) -> Motif:
        """The motif that a graph has after time and all edges are reversed."""
        return Motif(tuple((b, a) for a, b in reversed(self.edges)), f"{self.name}-reversed")

    def anchors(self) -> list[Anchor]:
        """All anchors that hold the earliest edge: spanning 3-paths for four vertices, wedges for three."""
        found = []
        spots = range(len(self.edges))
        if len(self.vertices) == 3:
            for base, other in product(spots, spots):
                (u, v), (x, y) = self.edges[base], self.edges[other]
                if base == other or 0 not in (base, other) or {u, v} == {x, y}:
                    continue
                pivot = u if u in (x, y) else v
                third = y if x == pivot else x
                cls = WedgeClass("src" if pivot == u else "dst", "+" if x == pivot else "-", "<" if other < base else ">")
                found.append(Anchor((base, other), cls, (u, v, third)))
        else:
            for one, center, three in product(spots, spots, spots):
                if 0 not in (one, center, three) or len({one, center, three}) < 3:
                    continue
                u, v = self.edges[center]
                e1, e3 = self.edges[one], self.edges[three]
                if u not in e1 or v not in e3:
                    continue
                x, y = e1[1] if e1[0] == u else e1[0], e3[1] if e3[0] == v else e3[0]
                if len({x, u, v, y}) < 4:
                    continue
                cls = PathClass("+" if e1[0] == u else "-", "+" if e3[0] == v else "-", "<" if one < center else ">", "<" if three < center else ">")
                found.append(Anchor((one, center, three), cls, (x, u, v, y)))
        first = set(range(len(found[0].positions))) if found else set()
        return sorted(found, key=lambda a: (set(a.positions) != first, a.positions))

    def anchor(self, policy: str | tuple[int, ...] = "first") -> Anchor:
        """The first anchor, or the one at the given positions."""
        found = self.anchors()
        if not found:
            raise AnchorError(f"{self.name or self.edges} has no anchor: a star has no spanning 3-path; use an exact counter or sampler='hub'")
        if policy == "first":
            return found[0]
        for a in found:
            if a.positions == tuple(policy):
                return a
        raise AnchorError(f"no anchor at {policy}")


#: Edges in time order. Shapes that the text does not draw are our choice (README).
CATALOG = {
    name: Motif.parse(text, name)
    for name, text in {
        "M4-0": "AB BC CD DA",
        "M4-1": "AB BC CD DC CB BA AB BC CD",
        "M4-2": "AB BC CD DA AD DC CB BA",
        "M4-3": "AB BC CD DB BD DC CB BA",
        "M4-4": "AB BC CD DA AC CA AD DC CB BA",
        "M4-5": "AB BC CD DA AC",
        "M3-0": "AB BC CA AC CB BA",
        "M3-1": "AB AC BC CB CA BA",
        "TRI": "AB BC CA",
        "PATH": "AB BC CD",
        "PAW": "AB BC CA AD",
        "K4": "AB BC CD DA AC BD",
        "LATE": "AB CD BC DA",
        "SPLIT": "AB DA BC CD",
        "STAR": "AB AC AD",
    }.items()
}
#: The eight motifs of the experiments.
EIGHT = ("M3-0", "M3-1", "M4-0", "M4-1", "M4-2", "M4-3", "M4-4", "M4-5")


def motif(which: str | Motif) -> Motif:
    return which if isinstance(which, Motif) else CATALOG[which]


def parse_delta(delta: int | str, unit: str = "us") -> int:
    """A window in the unit of t: an integer, or '4W', '1D', '6H', '90S' for microseconds ('us'), seconds ('s') or days ('day')."""
    if isinstance(delta, int):
        return delta
    seconds = {"W": 604_800, "D": 86_400, "H": 3_600, "M": 60, "S": 1}[delta[-1].upper()] * int(delta[:-1])
    return {"us": seconds * 1_000_000, "s": seconds, "day": seconds // 86_400}[unit]
