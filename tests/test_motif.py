"""Patterns, anchors and classes."""

import pytest

from tmotif.functions.motif import CATALOG, AnchorError, Motif, PathClass, WedgeClass, parse_delta

#: name: edges, free edges, anchors, classes, first choice, its class
TABLE = {
    "M3-0": (6, 4, 8, 8, (0, 1), "dst+>"),
    "M3-1": (6, 4, 8, 8, (0, 1), "src+>"),
    "TRI": (3, 1, 4, 4, (0, 1), "dst+>"),
    "M4-0": (4, 1, 3, 3, (0, 1, 2), "-+<>"),
    "M4-1": (9, 6, 9, 6, (0, 1, 2), "-+<>"),
    "M4-2": (8, 5, 12, 11, (0, 1, 2), "-+<>"),
    "M4-3": (8, 5, 8, 5, (0, 1, 2), "-+<>"),
    "M4-4": (10, 7, 16, 14, (0, 1, 2), "-+<>"),
    "M4-5": (5, 2, 4, 4, (0, 1, 2), "-+<>"),
    "PATH": (3, 0, 1, 1, (0, 1, 2), "-+<>"),
    "PAW": (4, 1, 1, 1, (3, 0, 1), "++>>"),
    "K4": (6, 3, 6, 6, (0, 1, 2), "-+<>"),
    "LATE": (4, 1, 3, 2, (0, 2, 1), "-+<<"),
    "SPLIT": (4, 1, 3, 3, (1, 0, 2), "-+>>"),
}


@pytest.mark.parametrize("name", TABLE)
def test_anchors(name):
    m = CATALOG[name]
    found = m.anchors()
    first = m.anchor()
    assert (len(m.edges), m.free_edges, len(found), len({a.cls for a in found}), first.positions, str(first.cls)) == TABLE[name]
    assert all(0 in a.positions for a in found)


def test_star_has_no_anchor():
    with pytest.raises(AnchorError):
        CATALOG["STAR"].anchor()


def test_validation():
    for bad in ("AA AB BC", "AB CD", "AB BA", "AB BC CD DE"):
        with pytest.raises(ValueError):
            Motif.parse(bad)
    assert Motif.parse("A>B, B>C, C>A").edges == (("A", "B"), ("B", "C"), ("C", "A"))


def test_classes_and_delta():
    assert len(set(map(str, PathClass.all()))) == 16 and len(set(map(str, WedgeClass.all()))) == 8
    assert parse_delta("4W", "s") == 4 * 604_800 and parse_delta("1D", "day") == 1 and parse_delta(7) == 7
