"""Indexes and sweeps over the boxes of one task: NumPy arrays in, index pairs (i of source, j of target) out.

Each takes source and target boxes as arrays of shape (n, 4): xmin, ymin, xmax, ymax, and finds all pairs whose closed
boxes meet. Trees are flat arrays (a node's box, first child, number of children), queried level by level for all
targets together.
"""

from __future__ import annotations

import numpy as np

Pairs = tuple[np.ndarray, np.ndarray]


def meet(s: np.ndarray, t: np.ndarray) -> np.ndarray:
    return (s[:, 0] <= t[:, 2]) & (t[:, 0] <= s[:, 2]) & (s[:, 1] <= t[:, 3]) & (t[:, 1] <= s[:, 3])


def ranges(lo: np.ndarray, hi: np.ndarray) -> Pairs:
    """All (row, k) with lo[row] <= k < hi[row]."""
    size = np.maximum(hi - lo, 0)
    row = np.repeat(np.arange(len(lo)), size)
    return row, np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size) + np.repeat(lo, size)


def nested(s: np.ndarray, t: np.ndarray, chunk: int = 4_000_000) -> Pairs:
    out = []
    step = max(1, chunk // max(1, len(t)))
    for at in range(0, len(s), step):
        a = s[at : at + step, None, :]
        ok = (a[..., 0] <= t[None, :, 2]) & (t[None, :, 0] <= a[..., 2]) & (a[..., 1] <= t[None, :, 3]) & (t[None, :, 1] <= a[..., 3])
        i, j = np.nonzero(ok)
        out.append((i + at, j))
    return _joined(out)


def _joined(parts: list[Pairs]) -> Pairs:
    if not parts:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return np.concatenate([p[0] for p in parts]).astype(np.int64), np.concatenate([p[1] for p in parts]).astype(np.int64)


#: Index pairs that a sweep or grid holds at once before the exact test.
CHUNK = 2_000_000


def chunked(lo: np.ndarray, hi: np.ndarray, chunk: int = CHUNK):
    """`ranges` in runs of rows of about `chunk` index pairs, so that what is held does not grow with the overlaps."""
    total = np.cumsum(np.maximum(hi - lo, 0))
    at = 0
    while at < len(lo):
        to = max(at + 1, int(np.searchsorted(total, (total[at - 1] if at else 0) + chunk, "right")))
        row, k = ranges(lo[at:to], hi[at:to])
        yield row + at, k
        at = to


def sweep_list(s: np.ndarray, t: np.ndarray) -> Pairs:
    """Plane sweep with one list per side: when the line stops at an xmin, the active boxes of the other side pair up."""
    so, to = np.argsort(s[:, 0], kind="stable"), np.argsort(t[:, 0], kind="stable")
    sx, tx = s[so, 0], t[to, 0]
    out = []

    def keep(i, j):
        ok = (s[i, 1] <= t[j, 3]) & (t[j, 1] <= s[i, 3])
        out.append((i[ok], j[ok]))

    # Boxes that start while this one is active; ties count for the source's stop.
    for i, k in chunked(np.searchsorted(tx, sx, "left"), np.searchsorted(tx, s[so, 2], "right")):
        keep(so[i], to[k])
    for j, k in chunked(np.searchsorted(sx, tx, "right"), np.searchsorted(sx, t[to, 2], "right")):
        keep(so[k], to[j])
    return _joined(out)


def sweep_stripes(s: np.ndarray, t: np.ndarray, width: float | None = None) -> Pairs:
    """Plane sweep with one pair of lists per stripe: stripes of the mean source height in y, swept along x in each.

    A pair is kept in the stripe of the larger ymin.
    """
    if not len(s) or not len(t):
        return _joined([])
    width = width or float((s[:, 3] - s[:, 1]).mean()) or float((s[:, 2] - s[:, 0]).mean()) or 1.0
    cell = lambda v: np.floor(v / width).astype(np.int64)
    si, sk = ranges(cell(s[:, 1]), cell(s[:, 3]) + 1)
    ti, tk = ranges(cell(t[:, 1]), cell(t[:, 3]) + 1)
    # Stripes are laid end to end along x, so one sweep goes through all of them.
    xs = np.unique(np.concatenate([s[:, 0], s[:, 2], t[:, 0], t[:, 2]]))
    rank = lambda v, k: k * len(xs) + np.searchsorted(xs, v)
    s1, s2, t1, t2 = rank(s[si, 0], sk), rank(s[si, 2], sk), rank(t[ti, 0], tk), rank(t[ti, 2], tk)
    so, to = np.argsort(s1, kind="stable"), np.argsort(t1, kind="stable")
    out = []

    def keep(a, b):
        i, j = si[a], ti[b]
        ok = (s[i, 1] <= t[j, 3]) & (t[j, 1] <= s[i, 3]) & (np.maximum(cell(s[i, 1]), cell(t[j, 1])) == sk[a])
        out.append((i[ok], j[ok]))

    for i, k in chunked(np.searchsorted(t1[to], s1[so], "left"), np.searchsorted(t1[to], s2[so], "right")):
        keep(so[i], to[k])
    for j, k in chunked(np.searchsorted(s1[so], t1[to], "right"), np.searchsorted(s1[so], t2[to], "right")):
        keep(so[k], to[j])
    return _joined(out)


class Tree:
    """Levels from the root down: boxes, first child and number of children; leaves point into `order`."""

    def __init__(self, levels: list[tuple[np.ndarray, np.ndarray, np.ndarray]], order: np.ndarray, items: np.ndarray):
        self.levels, self.order, self.items = levels, order, items
        self.visited = 0

    def nbytes(self) -> int:
        return sum(a.nbytes for level in self.levels for a in level) + self.order.nbytes

    def boxes(self, level: int, node: np.ndarray, parent: np.ndarray) -> np.ndarray:
        return self.levels[level][0][node]

    def query(self, t: np.ndarray) -> Pairs:
        if not len(self.items) or not len(t):
            return _joined([])
        q = np.arange(len(t))
        node = np.zeros(len(t), np.int64)
        parent = self.boxes(0, node, None)
        for depth in range(len(self.levels)):
            box = self.boxes(depth, node, parent)
            self.visited += len(q)
            ok = meet(box, t[q])
            q, node, box = q[ok], node[ok], box[ok]
            _, first, size = self.levels[depth]
            row, child = ranges(first[node], first[node] + size[node])
            q, node, parent = q[row], child, box[row]
        i = self.order[node]
        ok = meet(self.items[i], t[q])
        return i[ok], q[ok]


def _cover(items: np.ndarray, first: np.ndarray, size: np.ndarray) -> np.ndarray:
    lo = np.minimum.reduceat(items[:, :2], first)
    hi = np.maximum.reduceat(items[:, 2:], first)
    return np.column_stack([lo, hi])


def str_order(boxes: np.ndarray, capacity: int) -> np.ndarray:
    """Sort-tile-recursive packing: slices by x centre, then by y centre within a slice."""
    n = len(boxes)
    x, y = boxes[:, 0] + boxes[:, 2], boxes[:, 1] + boxes[:, 3]
    slices = max(1, int(np.ceil(np.sqrt(n / capacity))))
    order = np.argsort(x, kind="stable")
    part = np.empty(n, np.int64)
    part[order] = np.arange(n) // (-(-n // slices))
    return np.lexsort((y, part))


def str_tree(s: np.ndarray, capacity: int = 16) -> Tree:
    n = len(s)
    order = str_order(s, capacity) if n else np.zeros(0, np.int64)
    levels, items = [], s[order]
    if not n:
        return Tree([(np.zeros((1, 4)), np.zeros(1, np.int64), np.zeros(1, np.int64))], order, s)
    while True:
        first = np.arange(0, len(items), capacity)
        size = np.diff(np.append(first, len(items)))
        items = _cover(items, first, size)
        levels.insert(0, (items, first, size))
        if len(items) == 1:
            return Tree(levels, order, s)


class CompressedTree(Tree):
    """A packed tree that stores a node's box relative to its parent in a few bits, rounded outwards."""

    def __init__(self, tree: Tree, bits: int = 8):
        steps = (1 << bits) - 1
        kind = np.uint8 if bits <= 8 else np.uint16
        levels, above = [], None
        for box, first, size in tree.levels:
            if above is None:
                levels.append((box.copy(), first.astype(np.int32), size.astype(np.uint16)))
                exact = box
            else:
                parent = np.repeat(above, self_sizes, axis=0)  # noqa: F821
                span = np.where(parent[:, 2:] > parent[:, :2], parent[:, 2:] - parent[:, :2], 1.0)
                lo = np.clip(np.floor((box[:, :2] - parent[:, :2]) / span * steps) - 1, 0, steps)
                hi = np.clip(np.ceil((box[:, 2:] - parent[:, :2]) / span * steps) + 1, 0, steps)
                levels.append((np.column_stack([lo, hi]).astype(kind), first.astype(np.int32), size.astype(np.uint16)))
                exact = np.column_stack([parent[:, :2] + lo / steps * span, parent[:, :2] + hi / steps * span])
                exact[:, :2][lo == 0] = parent[:, :2][lo == 0]
                exact[:, 2:][hi == steps] = parent[:, 2:][hi == steps]
            above, self_sizes = exact, size
        super().__init__(levels, tree.order.astype(np.int32), tree.items)
        self.steps = steps

    def boxes(self, level: int, node: np.ndarray, parent: np.ndarray) -> np.ndarray:
        raw = self.levels[level][0][node]
        if level == 0:
            return raw
        span = np.where(parent[:, 2:] > parent[:, :2], parent[:, 2:] - parent[:, :2], 1.0)
        lo, hi = raw[:, :2].astype(float), raw[:, 2:].astype(float)
        out = np.column_stack([parent[:, :2] + lo / self.steps * span, parent[:, :2] + hi / self.steps * span])
        out[:, :2][lo == 0] = parent[:, :2][lo == 0]
        out[:, 2:][hi == self.steps] = parent[:, 2:][hi == self.steps]
        return out


def cr_tree(s: np.ndarray, capacity: int = 16, bits: int = 8) -> CompressedTree:
    return CompressedTree(str_tree(s, capacity), bits)


def r_tree(s: np.ndarray, capacity: int = 16) -> Tree:
    """Boxes are inserted one by one; a full node splits around its two largest entries, others go where a box grows least."""
    class Node:
        __slots__ = ("box", "kids", "leaf")

        def __init__(self, kids, leaf):
            self.kids, self.leaf = kids, leaf
            self.fit()

        def fit(self):
            b = s[self.kids] if self.leaf else np.array([k.box for k in self.kids])
            self.box = (b[:, 0].min(), b[:, 1].min(), b[:, 2].max(), b[:, 3].max())

    def area(b):
        return (b[2] - b[0]) * (b[3] - b[1])

    def union(a, b):
        return (min(a[0], b[0]), min(a[1], b[1]), max(a[2], b[2]), max(a[3], b[3]))

    def box_of(node, k):
        return tuple(s[k]) if node.leaf else k.box

    def split(node):
        by = sorted(node.kids, key=lambda k: -area(box_of(node, k)))
        parts = [[by[0]], [by[1]]]
        boxes = [box_of(node, by[0]), box_of(node, by[1])]
        for k in by[2:]:
            b = box_of(node, k)
            grow = [area(union(boxes[p], b)) - area(boxes[p]) for p in (0, 1)]
            p = 0 if (grow[0], len(parts[0])) <= (grow[1], len(parts[1])) else 1
            parts[p].append(k)
            boxes[p] = union(boxes[p], b)
        return [Node(p, node.leaf) for p in parts]

    root = None
    for i in range(len(s)):
        b = tuple(s[i])
        if root is None:
            root = Node([i], True)
            continue
        path, node = [], root
        while not node.leaf:
            path.append(node)
            node.box = union(node.box, b)
            node = min(node.kids, key=lambda k: (area(union(k.box, b)) - area(k.box), area(k.box)))
        node.kids.append(i)
        node.box = union(node.box, b)
        while len(node.kids) > capacity:
            two = split(node)
            if not path:
                root = Node(two, False)
                break
            up = path.pop()
            up.kids = [k for k in up.kids if k is not node] + two
            node = up
    return _flattened(root, s)


def _flattened(root, s: np.ndarray) -> Tree:
    if root is None:
        return str_tree(s)
    levels, now = [], [root]
    while True:
        box = np.array([n.box for n in now], float).reshape(-1, 4)
        size = np.array([len(n.kids) for n in now])
        first = np.cumsum(size) - size
        levels.append((box, first, size))
        if now[0].leaf:
            return Tree(levels, np.array([k for n in now for k in n.kids], np.int64), s)
        now = [k for n in now for k in n.kids]


class QuadTree:
    """Four quadrants to a cell, split when it holds more than the capacity; a box lies in every leaf that it meets."""

    def __init__(self, s: np.ndarray, capacity: int = 16, max_depth: int = 16):
        self.items = s
        self.nodes: list[tuple[tuple[float, float, float, float], int, np.ndarray | None]] = []
        self.visited = 0
        if len(s):
            x, y = s[:, 0].min(), s[:, 1].min()
            size = max(s[:, 2].max() - x, s[:, 3].max() - y) or 1.0
            todo = [((x, y, x + size, y + size), np.arange(len(s)), 0, -1)]
            while todo:
                cell, own, depth, parent = todo.pop()
                here = len(self.nodes)
                if parent >= 0:
                    self.nodes[parent][1].append(here)
                mx, my = (cell[0] + cell[2]) / 2, (cell[1] + cell[3]) / 2
                if len(own) <= capacity or depth >= max_depth:
                    self.nodes.append((cell, [], own))
                    continue
                self.nodes.append((cell, [], None))
                for q in ((mx, my, cell[2], cell[3]), (cell[0], my, mx, cell[3]), (mx, cell[1], cell[2], my), (cell[0], cell[1], mx, my)):
                    b = s[own]
                    inside = (b[:, 0] <= q[2]) & (b[:, 2] >= q[0]) & (b[:, 1] <= q[3]) & (b[:, 3] >= q[1])
                    if inside.any():
                        todo.append((q, own[inside], depth + 1, here))

    def nbytes(self) -> int:
        return sum(48 + 8 * len(k) + (o.nbytes if o is not None else 0) for _, k, o in self.nodes)

    def query(self, t: np.ndarray) -> Pairs:
        out = []
        todo = [(0, np.arange(len(t)))] if self.nodes and len(t) else []
        while todo:
            n, q = todo.pop()
            cell, kids, own = self.nodes[n]
            b = t[q]
            self.visited += len(q)
            q = q[(b[:, 0] <= cell[2]) & (b[:, 2] >= cell[0]) & (b[:, 1] <= cell[3]) & (b[:, 3] >= cell[1])]
            if not len(q):
                continue
            if own is None:
                todo += [(k, q) for k in kids]
                continue
            i, j = nested(self.items[own], t[q])
            out.append((own[i], q[j]))
        i, j = _joined(out)
        if len(i):
            code = np.unique(i * len(t) + j)
            i, j = code // len(t), code % len(t)
        return i, j


def grid_index(s: np.ndarray, t: np.ndarray, w: float, h: float) -> Pairs:
    """A local grid with the given tile: shared tiles, then the reference point's tile and the box test."""
    if not len(s) or not len(t):
        return _joined([])
    cell = lambda b: (np.floor(b[:, 0] / w).astype(np.int64), np.floor(b[:, 2] / w).astype(np.int64), np.floor(b[:, 1] / h).astype(np.int64), np.floor(b[:, 3] / h).astype(np.int64))

    def tiles(b):
        x1, x2, y1, y2 = cell(b)
        i, x = ranges(x1, x2 + 1)
        k, y = ranges(y1[i], y2[i] + 1)
        return i[k], x[k], y

    si, sx, sy = tiles(s)
    ti, tx, ty = tiles(t)
    base, span = min(sy.min(), ty.min()), max(sy.max(), ty.max()) - min(sy.min(), ty.min()) + 1
    sk, tk = (sx - min(sx.min(), tx.min())) * span + sy - base, (tx - min(sx.min(), tx.min())) * span + ty - base
    so, to = np.argsort(sk, kind="stable"), np.argsort(tk, kind="stable")
    out = []
    for i, k in chunked(np.searchsorted(tk[to], sk[so], "left"), np.searchsorted(tk[to], sk[so], "right")):
        a, b, x, y = si[so][i], ti[to][k], sx[so][i], sy[so][i]
        own = (np.floor(np.maximum(s[a, 0], t[b, 0]) / w) == x) & (np.floor(np.minimum(s[a, 3], t[b, 3]) / h) == y)
        a, b = a[own], b[own]
        ok = meet(s[a], t[b])
        out.append((a[ok], b[ok]))
    return _joined(out)


#: Local joins by name, (source boxes, target boxes, node capacity, tile) -> pairs; `register_local_index` adds to them.
LOCAL = {
    "nested": lambda s, t, capacity, tile: nested(s, t),
    "list": lambda s, t, capacity, tile: sweep_list(s, t),
    "stripes": lambda s, t, capacity, tile: sweep_stripes(s, t),
    "rtree": lambda s, t, capacity, tile: str_tree(s, capacity).query(t),
    "rtree_inserted": lambda s, t, capacity, tile: r_tree(s, capacity).query(t),
    "str": lambda s, t, capacity, tile: str_tree(s, capacity).query(t),
    "crtree": lambda s, t, capacity, tile: cr_tree(s, capacity).query(t),
    "quadtree": lambda s, t, capacity, tile: QuadTree(s, capacity).query(t),
    "grid": lambda s, t, capacity, tile: grid_index(s, t, *tile),
}


def register_local_index(name: str, join) -> None:
    """Adds a local join: any callable (source boxes, target boxes, capacity, tile) -> (i, j)."""
    LOCAL[name] = join


def local_of(kind: str):
    """A local join by name; looked up where a join is planned, since tasks may not have what was registered there."""
    if kind not in LOCAL:
        raise ValueError(f"no local join {kind}; there are {sorted(LOCAL)}")
    return LOCAL[kind]


def local_join(kind: str, s: np.ndarray, t: np.ndarray, capacity: int = 16, tile: tuple[float, float] | None = None) -> Pairs:
    return local_of(kind)(s, t, capacity, tile)
