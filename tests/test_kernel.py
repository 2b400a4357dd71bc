"""Matrices against the driver-side topology library, in integers and in doubles, and hand-made cases."""

import random

import numpy as np
import pyarrow as pa
import pytest

from spatial_links.functions import kernel as K


def rect(x, y, w, h):
    return [(x, y), (x + w, y), (x + w, y + h), (x, y + h), (x, y)]


def wkt(rings, polygon):
    f = lambda q: "(" + ", ".join(f"{x!r} {y!r}" for x, y in q) + ")"
    return "POLYGON (" + ", ".join(map(f, rings)) + ")" if polygon else "LINESTRING " + f(rings[0])


def shape(rng, real):
    g = lambda n=6: rng.random() * n if real else float(rng.randint(0, n))
    k = rng.randrange(7)
    if k == 0:
        return [rect(g(), g(), 1 + g(4), 1 + g(4))], True
    if k == 1:
        x, y, w, h = g(), g(), 3 + g(3), 3 + g(3)
        return [rect(x, y, w, h), rect(x + 1, y + 1, w - 2, h - 2)[::-1]], True
    if k == 2:
        while True:
            t = [(g(), g()) for _ in range(3)]
            if abs((t[1][0] - t[0][0]) * (t[2][1] - t[0][1]) - (t[1][1] - t[0][1]) * (t[2][0] - t[0][0])) > 1e-3:
                return [[*t, t[0]]], True
    if k == 3:
        return [[(float(x), g()) for x in sorted(rng.sample(range(9), rng.randint(2, 4)))]], False
    x, y = g(), g()
    if k == 4:
        return [[(x, y), (x + 1 + g(3), y)]], False
    if k == 5:
        w = 1 + g(3)
        return [[(x, y), (x + w, y), (x + w, y + 1 + g(3))]], False
    return [rect(x, y, 1 + g(3), 1 + g(3))], False


def relate(pairs):
    col = lambda s, i: pa.array([[p[i] for r in q[s][0] for p in r] for q in pairs], pa.list_(pa.float64()))
    ends = lambda s: pa.array([np.cumsum([len(r) for r in q[s][0]]).tolist() for q in pairs], pa.list_(pa.int32()))
    flag = lambda s: np.array([q[s][1] for q in pairs], bool)
    return K.relate(flag(0), col(0, 0), col(0, 1), ends(0), flag(1), col(1, 0), col(1, 1), ends(1))


@pytest.mark.parametrize("real", [False, True])
def test_against_the_topology_library(spark, real):
    rng = random.Random(3)
    pairs = [(shape(rng, real), shape(rng, real)) for _ in range(600)]
    pairs += [(a, a) for a, _ in pairs[:60]]
    reader = spark._jvm.org.locationtech.jts.io.WKTReader()
    want = [str(reader.read(wkt(*a)).relate(reader.read(wkt(*b))).toString()) for a, b in pairs]
    assert relate(pairs) == want
    for (a, b), m in list(zip(pairs, want, strict=True))[::10]:
        assert K.relate_exact(a[0], a[1], b[0], b[1]) == m


def test_worked_examples():
    square = [rect(0.0, 0.0, 2.0, 2.0)], True
    assert relate([(square, ([[(0.0, 0.0), (2.0, 0.0)]], False))]) == ["FF2101FF2"]
    assert relate([(([[(0.0, 0.0), (2.0, 2.0)]], False), ([[(0.0, 2.0), (2.0, 0.0)]], False))]) == ["0F1FF0102"]
    assert relate([]) == []


def test_pieces_without_a_meeting_are_asked_once(monkeypatch):
    """A ring of 400 segments that crosses a box twice: a handful of points is looked for in the other, not one a segment."""
    comb = [(float(x), float(4 + x % 2)) for x in range(400)]
    ring = [[(0.0, 0.0), *comb, (399.0, 0.0), (0.0, 0.0)]], True
    asked, real = [], K._inside
    monkeypatch.setattr(K, "_inside", lambda poly, pair, x, y, doubt: asked.append(len(x)) or real(poly, pair, x, y, doubt))
    box, apart, hole = ([rect(10.0, -3.0, 300.0, 5.0)], True), ([rect(500.0, 500.0, 2.0, 2.0)], True), ([rect(1.0, 1.0, 390.0, 2.0)], True)
    assert relate([(ring, box), (ring, apart), (ring, hole)]) == ["212101212", "FF2FF1212", "212FF1FF2"]
    assert sum(asked) < 40
