"""Nine-intersection matrices of many geometry pairs at once.

Both boundaries (or lines) of every pair are cut where they meet the other geometry; a piece lies on the other
boundary, inside or outside of it, and all matrix entries follow from which pieces and meeting points exist:

* two polygons: interiors share an area if a piece of one boundary is inside the other, or both boundaries coincide;
* line and polygon: pieces of the line give its row, uncovered pieces of the ring give the polygon's;
* two lines: covered pieces give dimension 1, meeting points dimension 0.

The work is done on flat arrays over a whole Arrow batch. Orientations of integers below 2**25 are exact in doubles; any
other sign that is not certain sends its pair to `relate_exact`, the same method in rational numbers.
"""

from __future__ import annotations

from fractions import Fraction

import numpy as np
import pyarrow as pa

MATRIX = "II IB IE BI BB BE EI EB EE".split()
_EXACT = float(1 << 25)
_CHUNK = 300_000  # products of points; what they take stays near the processor


class Side:
    """One geometry of each pair, flattened: coordinates, rings and segments with their pair."""

    def __init__(self, polygon: np.ndarray, xs, ys, ends):
        n = len(polygon)
        self.n, self.polygon = n, polygon
        self.x, off = _flat(xs)
        self.y, _ = _flat(ys)
        ends_v, eoff = _flat(ends)
        self.off = off
        size = np.diff(off)
        self.pair_of_point = np.repeat(np.arange(n), size)
        # A segment starts at every point but the last of each ring.
        last = np.zeros(len(self.x), bool)
        if len(ends_v):
            last[off[np.repeat(np.arange(n), np.diff(eoff))] + ends_v.astype(np.int64) - 1] = True
        start = np.flatnonzero(~last)
        self.pair = self.pair_of_point[start]
        self.x1, self.y1, self.x2, self.y2 = self.x[start], self.y[start], self.x[start + 1], self.y[start + 1]
        self.lx, self.hx, self.ly, self.hy = np.minimum(self.x1, self.x2), np.maximum(self.x1, self.x2), np.minimum(self.y1, self.y2), np.maximum(self.y1, self.y2)
        self.fresh = (start == 0) | last[start - 1]  # the first segment of a ring or a line
        # The box of each geometry; without any point, one that meets all.
        some, low, high = bool(n) and bool(size.all()), np.full(n, -np.inf), np.full(n, np.inf)
        self.box = [f.reduceat(v, off[:-1]) if some else e for f, v, e in ((np.fmin, self.x, low), (np.fmax, self.x, high), (np.fmin, self.y, low), (np.fmax, self.y, high))]
        self.soff = np.searchsorted(self.pair, np.arange(n + 1))
        first, end = off[:-1], off[1:] - 1
        self.closed = (self.x[first] == self.x[end]) & (self.y[first] == self.y[end])
        self.ends = ~polygon & ~self.closed  # has two boundary points


def _flat(lists) -> tuple[np.ndarray, np.ndarray]:
    if isinstance(lists, pa.ChunkedArray):
        lists = lists.combine_chunks()
    off = np.frombuffer(lists.buffers()[1], np.int32)[lists.offset : lists.offset + len(lists) + 1].astype(np.int64)
    return lists.values.to_numpy(zero_copy_only=False)[off[0] : off[-1]], off - off[0]


def _ranges(lo, hi) -> tuple[np.ndarray, np.ndarray]:
    """All (k, j) with j in [lo[k], hi[k])."""
    size = hi - lo
    return np.repeat(np.arange(len(size)), size), np.arange(size.sum()) + np.repeat(lo - (np.cumsum(size) - size), size)


def _near(s: Side, other: Side) -> np.ndarray:
    """The segments of s whose boxes meet that of the pair's other geometry."""
    x1, x2, y1, y2 = (v[s.pair] for v in other.box)
    return np.flatnonzero((s.lx <= x2) & (s.hx >= x1) & (s.ly <= y2) & (s.hy >= y1))


def _turn(ax, ay, bx, by, cx, cy):
    """Orientation of c against a->b, and a bound on its error."""
    p, q = (bx - ax) * (cy - ay), (by - ay) * (cx - ax)
    return p - q, 1e-15 * (np.abs(p) + np.abs(q))


def relate(a_polygon, a_xs, a_ys, a_ends, b_polygon, b_xs, b_ys, b_ends) -> list[str]:
    """The nine-character matrices of pairs given as Arrow list columns and polygon flags."""
    out: list[str] = []
    n = len(a_polygon)
    work = np.maximum(1, _sizes(a_xs) * _sizes(b_xs)) if n else np.zeros(0, np.int64)
    at = 0
    while at < n:
        to = at + max(1, int(np.searchsorted(np.cumsum(work[at:]), _CHUNK)))
        cut = slice(at, to)
        a = Side(a_polygon[cut], *(c.slice(at, to - at) for c in (a_xs, a_ys, a_ends)))
        b = Side(b_polygon[cut], *(c.slice(at, to - at) for c in (b_xs, b_ys, b_ends)))
        out += _relate(a, b)
        at = to
    return out


def _sizes(lists) -> np.ndarray:
    return np.diff(_flat(lists)[1])


def _relate(a: Side, b: Side) -> list[str]:
    n = a.n
    doubt = np.zeros(n, bool)
    small = np.ones(n, bool)
    for s in (a, b):
        for v in (s.x, s.y):
            bad = (np.abs(v) >= _EXACT) | (v != np.floor(v))
            small &= np.bincount(s.pair_of_point, weights=bad, minlength=n) == 0
    # Segments that can meet: their boxes do, and each meets the box of the other geometry.
    ka, kb = _near(a, b), _near(b, a)
    at = np.searchsorted(b.pair[kb], np.arange(n + 1))
    i, j = _ranges(at[a.pair[ka]], at[a.pair[ka] + 1])
    near = (a.lx[ka][i] <= b.hx[kb][j]) & (a.hx[ka][i] >= b.lx[kb][j])
    i, j = i[near], j[near]
    near = (a.ly[ka][i] <= b.hy[kb][j]) & (a.hy[ka][i] >= b.ly[kb][j])
    i, j = ka[i[near]], kb[j[near]]
    own = a.pair[i]
    d1, e1 = _turn(b.x1[j], b.y1[j], b.x2[j], b.y2[j], a.x1[i], a.y1[i])
    d2, e2 = _turn(b.x1[j], b.y1[j], b.x2[j], b.y2[j], a.x2[i], a.y2[i])
    d3, e3 = _turn(a.x1[i], a.y1[i], a.x2[i], a.y2[i], b.x1[j], b.y1[j])
    d4, e4 = _turn(a.x1[i], a.y1[i], a.x2[i], a.y2[i], b.x2[j], b.y2[j])
    unsure = ~small[own] & ((np.abs(d1) <= e1) | (np.abs(d2) <= e2) | (np.abs(d3) <= e3) | (np.abs(d4) <= e4))
    doubt[own[unsure]] = True
    line = (d1 == 0) & (d2 == 0)
    cross = ~line & ((d1 <= 0) & (d2 >= 0) | (d1 >= 0) & (d2 <= 0)) & ((d3 <= 0) & (d4 >= 0) | (d3 >= 0) & (d4 <= 0))
    ci, cj = i[cross], j[cross]
    with np.errstate(divide="ignore", invalid="ignore"):
        ct, cu = d1[cross] / (d1[cross] - d2[cross]), d3[cross] / (d3[cross] - d4[cross])
    li, lj = i[line], j[line]
    wide = np.abs(a.x2[li] - a.x1[li]) >= np.abs(a.y2[li] - a.y1[li])
    pick = lambda s, k, w, end: np.where(w, (s.x1, s.x2)[end][k], (s.y1, s.y2)[end][k])
    a1, a2, b1, b2 = pick(a, li, wide, 0), pick(a, li, wide, 1), pick(b, lj, wide, 0), pick(b, lj, wide, 1)
    lo, hi = np.maximum(np.minimum(a1, a2), np.minimum(b1, b2)), np.minimum(np.maximum(a1, a2), np.maximum(b1, b2))
    ok = lo <= hi
    li, lj, lo, hi, a1, a2, b1, b2 = (v[ok] for v in (li, lj, lo, hi, a1, a2, b1, b2))
    with np.errstate(divide="ignore", invalid="ignore"):
        at = [(lo - a1) / (a2 - a1), (hi - a1) / (a2 - a1)]
        bt = [(lo - b1) / (b2 - b1), (hi - b1) / (b2 - b1)]
    # Meeting points: (segment of a, parameter, segment of b, parameter).
    mi, mj = np.concatenate([ci, li, li]), np.concatenate([cj, lj, lj])
    mt, mu = np.concatenate([ct, *at]), np.concatenate([cu, *bt])
    a_in, a_on, a_out = _pieces(a, b, mi, mt, li, np.minimum(*at), np.maximum(*at), small, doubt)
    b_in, b_on, b_out = _pieces(b, a, mj, mu, lj, np.minimum(*bt), np.maximum(*bt), small, doubt)

    pair = a.pair[mi]
    a_end, a_hit = _end_hits(a, mi, mt)
    b_end, b_hit = _end_hits(b, mj, mu)
    has = lambda flag: np.bincount(pair[flag], minlength=n) > 0
    a_bound, b_bound = a.polygon[pair] | a_end, b.polygon[pair] | b_end
    p_ii, p_ib, p_bi, p_bb = has(~a_bound & ~b_bound), has(~a_bound & b_bound), has(a_bound & ~b_bound), has(a_bound & b_bound)
    ends_in_b, ends_out_b = _loose_ends(a, b, a_hit, small, doubt)
    ends_in_a, ends_out_a = _loose_ends(b, a, b_hit, small, doubt)

    m = np.full((9, n), -1, np.int8)
    m[8] = 2
    put = lambda k, flag, dim: np.maximum(m[k], np.where(flag, dim, -1), out=m[k])
    pa_, pb = a.polygon, b.polygon
    both, la, lb, lines = pa_ & pb, ~pa_ & pb, pa_ & ~pb, ~pa_ & ~pb
    same = both & ~a_in & ~a_out & ~b_in & ~b_out & (a_on | b_on)
    area = both & (a_in | b_in | same)
    put(0, area, 2)
    put(1, both & b_in, 1)
    put(2, both & (a_out | b_in | ~area), 2)
    put(3, both & a_in, 1)
    put(4, both & (a_on | b_on), 1)
    put(4, both & p_bb, 0)
    put(5, both & a_out, 1)
    put(6, both & (b_out | a_in | ~area), 2)
    put(7, both & b_out, 1)
    for case, x_in, x_on, x_out, y_out, end_in, end_out, ib, bb, flip in (
        (la, a_in, a_on, a_out, b_out, ends_in_b, ends_out_b, p_ib, p_bb, False),
        (lb, b_in, b_on, b_out, a_out, ends_in_a, ends_out_a, p_bi, p_bb, True),
    ):
        # x is the line, y the polygon; for flip the matrix is transposed.
        k = [0, 3, 6, 1, 4, 7, 2, 5, 8] if flip else list(range(9))
        put(k[0], case & x_in, 1)
        put(k[1], case & x_on, 1)
        put(k[1], case & ib, 0)
        put(k[2], case & x_out, 1)
        put(k[3], case & end_in, 0)
        put(k[4], case & bb, 0)
        put(k[5], case & end_out, 0)
        put(k[6], case, 2)
        put(k[7], case & y_out, 1)
    put(0, lines & (a_on | b_on), 1)
    put(0, lines & p_ii, 0)
    put(1, lines & p_ib, 0)
    put(2, lines & a_out, 1)
    put(3, lines & p_bi, 0)
    put(4, lines & p_bb, 0)
    put(5, lines & ends_out_b, 0)
    put(6, lines & b_out, 1)
    put(7, lines & ends_out_a, 0)
    letters = np.array(list("F012"))[m.T + 1]
    out = letters.copy().view("<U9").ravel().tolist() if n else []
    for k in np.flatnonzero(doubt):
        out[k] = relate_exact(_rings(a, k), bool(pa_[k]), _rings(b, k), bool(pb[k]))
    return out


def _pieces(s: Side, other: Side, seg, t, on_seg, on_lo, on_hi, small, doubt):
    """Per pair: whether a piece of s lies inside, on, or outside the other geometry.

    Only a meeting point parts what lies inside from what lies outside, so of the pieces that follow one another without
    one between them the first is asked for all. Segments that meet nothing are one piece, and need no sort.
    """
    n, k = s.n, len(s.pair)
    met, first, last = np.zeros(k, bool), s.fresh.copy(), np.zeros(k, bool)
    met[seg], first[seg[t <= 0]], last[seg[t >= 1]] = True, True, True
    first[1:] |= last[:-1]
    every = np.flatnonzero(met)
    g = np.concatenate([every, every, seg, on_seg, on_seg])
    c = np.concatenate([np.zeros(len(every)), np.ones(len(every)), np.clip(t, 0, 1), on_lo, on_hi])
    d = np.concatenate([np.zeros(2 * len(every) + len(seg), np.int64), np.ones(len(on_seg), np.int64), np.full(len(on_seg), -1)])
    order = np.argsort(2 * g + c)  # cuts of a segment that this can't tell apart are as thin as those in doubt
    g, c, d = g[order], c[order], d[order]
    cover = np.cumsum(d)
    here = np.flatnonzero((g[1:] == g[:-1]) & (c[1:] != c[:-1]))
    thin = here[np.abs(c[here + 1] - c[here]) < 1e-9]
    doubt[s.pair[g[thin]]] = True
    here = here[c[here + 1] > c[here]]
    here = here[(c[here] > 0) | first[g[here]]]
    whole = np.flatnonzero(first & ~met)
    seg = np.concatenate([g[here], whole])
    mid = np.concatenate([(c[here] + c[here + 1]) / 2, np.full(len(whole), 0.5)])
    on = np.concatenate([cover[here] > 0, np.zeros(len(whole), bool)])
    pair = s.pair[seg]
    x, y = s.x1[seg] + mid * (s.x2[seg] - s.x1[seg]), s.y1[seg] + mid * (s.y2[seg] - s.y1[seg])
    inside = np.zeros(len(seg), bool)
    ask = np.flatnonzero(~on & other.polygon[pair])
    inside[ask] = _inside(other, pair[ask], x[ask], y[ask], doubt)
    has = lambda flag: np.bincount(pair[flag], minlength=n) > 0
    return has(inside), has(on), has(~on & ~inside)


def _inside(poly: Side, pair, x, y, doubt) -> np.ndarray:
    """Whether points off the boundary are in the polygon of their pair: rays to the right, half-open in y."""
    x1, x2, y1, y2 = (v[pair] for v in poly.box)
    ask = np.flatnonzero((x >= x1) & (x <= x2) & (y >= y1) & (y <= y2))
    at, j = _ranges(poly.soff[pair[ask]], poly.soff[pair[ask] + 1])
    span = (poly.y1[j] <= y[ask][at]) != (poly.y2[j] <= y[ask][at])
    at, j = ask[at[span]], j[span]
    px, py, y1, y2 = x[at], y[at], poly.y1[j], poly.y2[j]
    turn, error = _turn(poly.x1[j], y1, poly.x2[j], y2, px, py)
    doubt[pair[at[np.abs(turn) <= 4 * error]]] = True
    left = np.where(y2 > y1, turn > 0, turn < 0)
    return np.bincount(at[left], minlength=len(pair)) % 2 == 1


def _end_hits(s: Side, seg, t):
    """For meeting points: whether each is an end of an open line; per pair, which ends were met."""
    pair = s.pair[seg]
    first = s.ends[pair] & (seg == s.soff[pair]) & (t == 0)
    last = s.ends[pair] & (seg == s.soff[pair + 1] - 1) & (t == 1)
    hit = np.zeros((2, s.n), bool)
    hit[0, pair[first]] = True
    hit[1, pair[last]] = True
    return first | last, hit


def _loose_ends(s: Side, other: Side, hit, small, doubt):
    """Per pair: whether an end of an open line that is not on the other boundary lies inside, or outside."""
    n = s.n
    inside, outside = np.zeros(n, bool), np.zeros(n, bool)
    for k, at in enumerate((s.off[:-1], s.off[1:] - 1)):
        ask = np.flatnonzero(s.ends & ~hit[k])
        ins = np.zeros(len(ask), bool)
        poly = other.polygon[ask]
        ins[poly] = _inside(other, ask[poly], s.x[at[ask[poly]]], s.y[at[ask[poly]]], doubt)
        inside[ask[ins]] = True
        outside[ask[~ins]] = True
    return inside, outside


def _rings(s: Side, k: int) -> list[list[tuple[float, float]]]:
    """The rings (or the one line) of a pair's geometry, as point lists."""
    out, last = [], None
    for i in range(s.soff[k], s.soff[k + 1]):
        p, q = (s.x1[i], s.y1[i]), (s.x2[i], s.y2[i])
        if last != p or not out or (s.polygon[k] and len(out[-1]) > 1 and out[-1][0] == last):
            out.append([p])
        out[-1].append(q)
        last = q
    return out


def relate_exact(a: list, a_polygon: bool, b: list, b_polygon: bool) -> str:
    """The matrix of one pair in rational numbers; a and b are lists of rings of (x, y)."""

    def legs(rings):
        exact = [[(Fraction(float(x)), Fraction(float(y))) for x, y in r] for r in rings]
        return [(p, q) for r in exact for p, q in zip(r, r[1:], strict=False) if p != q]

    def turn(p, q, r):
        return (q[0] - p[0]) * (r[1] - p[1]) - (q[1] - p[1]) * (r[0] - p[0])

    def at(leg, t):
        return leg[0][0] + t * (leg[1][0] - leg[0][0]), leg[0][1] + t * (leg[1][1] - leg[0][1])

    def place(leg, p):
        k = 0 if leg[0][0] != leg[1][0] else 1
        return (p[k] - leg[0][k]) / (leg[1][k] - leg[0][k])

    def on(leg, p):
        return turn(*leg, p) == 0 and 0 <= place(leg, p) <= 1

    def within(legs_, p):
        odd = False
        for u, v in legs_:
            if (u[1] <= p[1]) != (v[1] <= p[1]) and (turn(u, v, p) > 0) == (v[1] > u[1]):
                odd = not odd
        return odd

    la, lb = legs(a), legs(b)
    meet = set()
    cuts = ({i: {Fraction(0), Fraction(1)} for i in range(len(la))}, {j: {Fraction(0), Fraction(1)} for j in range(len(lb))})
    for i, p in enumerate(la):
        for j, q in enumerate(lb):
            d1, d2, d3, d4 = turn(*q, p[0]), turn(*q, p[1]), turn(*p, q[0]), turn(*p, q[1])
            if d1 == d2 == 0:
                points = [x for x in (*p, *q) if on(p, x) and on(q, x)]
            elif d1 * d2 <= 0 and d3 * d4 <= 0:
                points = [at(p, d1 / (d1 - d2))]
            else:
                continue
            for x in points:
                meet.add(x)
                cuts[0][i].add(place(p, x))
                cuts[1][j].add(place(q, x))

    def pieces(mine, cut, other, polygon):
        found = set()
        for i, leg in enumerate(mine):
            ts = sorted(cut[i])
            for s, t in zip(ts, ts[1:], strict=False):
                p = at(leg, (s + t) / 2)
                found.add("on" if any(on(o, p) for o in other) else "in" if polygon and within(other, p) else "out")
        return found

    pa_, pb = pieces(la, cuts[0], lb, b_polygon), pieces(lb, cuts[1], la, a_polygon)

    def ends(rings, legs_, polygon):
        return set() if polygon or legs_[0][0] == legs_[-1][1] else {legs_[0][0], legs_[-1][1]}

    ea, eb = ends(a, la, a_polygon), ends(b, lb, b_polygon)
    m = dict.fromkeys(MATRIX, -1)
    m["EE"] = 2

    def put(k, flag, dim):
        if flag:
            m[k] = max(m[k], dim)

    for p in meet:
        put(("B" if a_polygon or p in ea else "I") + ("B" if b_polygon or p in eb else "I"), True, 0)
    on_a = {p for p in eb if any(on(x, p) for x in la)}
    on_b = {p for p in ea if any(on(x, p) for x in lb)}
    if a_polygon and b_polygon:
        area = "in" in pa_ or "in" in pb or pa_ == pb == {"on"}
        put("II", area, 2)
        put("IB", "in" in pb, 1)
        put("IE", "out" in pa_ or "in" in pb or not area, 2)
        put("BI", "in" in pa_, 1)
        put("BB", "on" in pa_, 1)
        put("BE", "out" in pa_, 1)
        put("EI", "out" in pb or "in" in pa_ or not area, 2)
        put("EB", "out" in pb, 1)
    elif a_polygon or b_polygon:
        flip = a_polygon
        x, y, ex, onx, poly = (pb, pa_, eb, on_a, la) if flip else (pa_, pb, ea, on_b, lb)
        name = (lambda k: k[::-1]) if flip else (lambda k: k)
        put(name("II"), "in" in x, 1)
        put(name("IB"), "on" in x, 1)
        put(name("IE"), "out" in x, 1)
        loose = ex - onx
        put(name("BI"), any(within(poly, p) for p in loose), 0)
        put(name("BE"), any(not within(poly, p) for p in loose), 0)
        put(name("EI"), True, 2)
        put(name("EB"), "out" in y, 1)
    else:
        put("II", "on" in pa_, 1)
        put("IE", "out" in pa_, 1)
        put("EI", "out" in pb, 1)
        put("BE", bool(ea - on_b), 0)
        put("EB", bool(eb - on_a), 0)
    return "".join("F012"[m[k] + 1] for k in MATRIX)
