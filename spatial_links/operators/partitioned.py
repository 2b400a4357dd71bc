"""Joins in three stages: disjoint cells from a sample, both sides dealt to the cells they meet, a local join per cell.

Cells cover the plane and exactly one of them owns a pair's reference point, so no shuffle is needed to remove repeats.
Only the sample (bounded by rows) and the cells reach the driver. How many cells there are follows from the rows of both
sides, and a cell that holds more than a task should is joined in blocks of both sides, so a task's rows are bounded.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spatial_links.functions.geometry import BOX, boxes_meet, prefixed
from spatial_links.operators import grid
from spatial_links.operators.grid import Stats
from spatial_links.operators.local_index import local_of, r_tree, ranges, str_tree
from spatial_links.plans.shared import written

SAMPLE_ROWS, BUCKET = 100_000, -1
#: Rows that a cell should hold, rows of one side that a task holds at most, and the fewest and most cells.
CELL_ROWS, BLOCK_ROWS, LEAST_CELLS, MOST_CELLS = 50_000, 200_000, 64, 25_000
BROADCAST_BYTES = 2 << 30
#: Rows of a block of the brute-force join, as a power of two.
BRUTE_BITS = 11
INF, FAR = float("inf"), 1e300


class SourceTooLarge(ValueError):
    """The source is over the limit of a broadcast join."""


def _points_in(boxes: np.ndarray) -> np.ndarray:
    return (boxes[:, :2] + boxes[:, 2:]) / 2


@dataclass(frozen=True)
class Cells:
    """Half-open boxes; with `bucket`, what lies in no cell goes to one overflow partition. Looked up by a packed tree."""

    boxes: np.ndarray
    bucket: bool = False

    def __len__(self) -> int:
        return len(self.boxes)

    def met(self, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(row, cell) for each cell whose closure meets each closed box."""
        if "tree" not in self.__dict__:
            self.__dict__["tree"] = str_tree(np.clip(self.boxes, -FAR, FAR), 8)
        k, i = self.__dict__["tree"].query(b)
        return i, k

    def __getstate__(self):
        return {"boxes": self.boxes, "bucket": self.bucket}

    def of(self, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(row, cell) for each cell that each closed box meets."""
        i, k = self.met(b)
        c = self.boxes
        ok = (b[i, 0] < c[k, 2]) & (b[i, 1] < c[k, 3])
        i, k = i[ok], k[ok]
        if self.bucket and len(b):
            lo, hi = c[:, :2].min(0), c[:, 2:].max(0)
            out = np.flatnonzero((b[:, 0] < lo[0]) | (b[:, 1] < lo[1]) | (b[:, 2] >= hi[0]) | (b[:, 3] >= hi[1]))
            i, k = np.concatenate([i, out]), np.concatenate([k, np.full(len(out), BUCKET)])
        return i, k

    def owns(self, cell: int, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        if cell == BUCKET:
            lo, hi = self.boxes[:, :2].min(0), self.boxes[:, 2:].max(0)
            return (x < lo[0]) | (y < lo[1]) | (x >= hi[0]) | (y >= hi[1])
        b = self.boxes[cell]
        return (x >= b[0]) & (x < b[2]) & (y >= b[1]) & (y < b[3])


@dataclass(frozen=True)
class LeafCells(Cells):
    """Closed boxes that may overlap and leave gaps, as the leaves of an R-tree do.

    The first cell that holds a reference point owns it, the bucket what none holds. Two boxes with the point in common
    both meet that cell; if none holds it, neither box lies in one cell, and every such box is in the bucket too.
    """

    def of(self, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        i, k = self.met(b)
        c = self.boxes[k]
        inside = np.zeros(len(b), bool)
        inside[i[(c[:, 0] <= b[i, 0]) & (c[:, 1] <= b[i, 1]) & (c[:, 2] >= b[i, 2]) & (c[:, 3] >= b[i, 3])]] = True
        out = np.flatnonzero(~inside)
        return np.concatenate([i, out]), np.concatenate([k, np.full(len(out), BUCKET)])

    def owns(self, cell: int, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        i, k = self.met(np.column_stack([x, y, x, y]))
        first = np.full(len(x), len(self.boxes))
        np.minimum.at(first, i, k)
        return first == (len(self.boxes) if cell == BUCKET else cell)


@dataclass(frozen=True)
class FixedCells(Cells):
    """Equal columns and rows over an extent, the outer ones reaching on without end: cells by arithmetic."""

    extent: tuple[float, float, float, float] = (0.0, 0.0, 1.0, 1.0)
    shape: tuple[int, int] = (1, 1)

    def __getstate__(self):
        return {"boxes": self.boxes, "bucket": self.bucket, "extent": self.extent, "shape": self.shape}

    def of(self, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        place = lambda v, axis: np.clip(np.searchsorted(self.edges(axis), v, "right") - 1, 0, self.shape[axis] - 1)
        i, x = ranges(place(b[:, 0], 0), place(b[:, 2], 0) + 1)
        k, y = ranges(place(b[i, 1], 1), place(b[i, 3], 1) + 1)
        return i[k], x[k] * self.shape[1] + y

    def edges(self, axis: int) -> np.ndarray:
        return np.linspace(self.extent[axis], np.nextafter(self.extent[axis + 2], INF), self.shape[axis] + 1)


@dataclass(frozen=True)
class Sample:
    """Stats of both sides, and the boxes of a hash sample of them with the rows that each stands for."""

    source: Stats
    target: Stats
    boxes: np.ndarray
    weight: float

    @property
    def rows(self) -> int:
        return self.source.rows + self.target.rows

    @property
    def points(self) -> np.ndarray:
        return _points_in(self.boxes)

    def extent(self) -> tuple[float, float, float, float]:
        return grid.joint(self.source, self.target).extent or (0.0, 0.0, 1.0, 1.0)

    def cells(self, share: float | None = None) -> int:
        """How many cells to aim at: by rows, or 1 / share."""
        return max(LEAST_CELLS, min(MOST_CELLS, -(-self.rows // CELL_ROWS))) if share is None else max(1, round(1 / share))

    def load(self, cells: Cells) -> dict[int, float]:
        """Rows of both sides dealt to each cell, as the sample shows (exact if it holds all rows)."""
        _, k = cells.of(self.boxes)
        ids, n = np.unique(k, return_counts=True)
        return dict(zip(ids.tolist(), (n * self.weight).tolist(), strict=True))


def sampled(source: DataFrame, target: DataFrame, rows: int = SAMPLE_ROWS, seed: int = 7) -> Sample:
    """Boxes of at most `rows` geometries of both sides together (the same each time): one aggregate, one collect."""
    s, t = grid.stats(source, target)
    both = source.select("gid", *BOX).unionByName(target.select("gid", *BOX))
    n = s.rows + t.rows
    if n > rows:
        both = both.where(F.pmod(F.xxhash64("gid", F.lit(seed)), F.lit(1_000_000_000)) < int(rows / n * 1_000_000_000) + 1)
    got = both.select(*BOX).limit(2 * rows).toArrow()
    boxes = np.column_stack([got.column(k).to_numpy() for k in range(4)]).reshape(-1, 4)
    boxes = boxes[np.lexsort(boxes.T)]
    return Sample(s, t, boxes, n / max(1, len(boxes)))


def _extended(boxes: list, points: np.ndarray, overflow: str) -> Cells:
    b = np.array(boxes, float).reshape(-1, 4)
    lo, hi = b[:, :2].min(0), b[:, 2:].max(0)
    if overflow == "extend":
        for k in (0, 1):
            b[b[:, k] == lo[k], k] = -INF
            b[b[:, k + 2] == hi[k], k + 2] = INF
    return Cells(b, overflow == "bucket")


def _extent(points: np.ndarray) -> tuple[float, float, float, float]:
    if not len(points):
        return 0.0, 0.0, 1.0, 1.0
    lo, hi = points.min(0), points.max(0)
    return lo[0], lo[1], np.nextafter(max(hi[0], lo[0]), INF), np.nextafter(max(hi[1], lo[1]), INF)


def kdb_cells(points: np.ndarray, capacity: int, overflow: str = "extend") -> Cells:
    """Median splits, alternating axes, until a cell holds at most `capacity` sample points."""
    out, todo = [], [(_extent(points), points, 0)]
    while todo:
        box, p, axis = todo.pop()
        cut = None
        for k in (axis, 1 - axis):
            if len(p) > capacity:
                m = float(np.median(p[:, k]))
                if box[k] < m < box[k + 2] and (p[:, k] < m).any():
                    cut = (k, m)
                    break
        if cut is None:
            out.append(box)
            continue
        k, m = cut
        low, high = list(box), list(box)
        low[k + 2] = high[k] = m
        todo += [(tuple(low), p[p[:, k] < m], 1 - k), (tuple(high), p[p[:, k] >= m], 1 - k)]
    return _extended(out, points, overflow)


def quadtree_cells(points: np.ndarray, capacity: int, overflow: str = "extend", max_depth: int = 12) -> Cells:
    out, todo = [], [(_extent(points), points, 0)]
    while todo:
        box, p, depth = todo.pop()
        mx, my = (box[0] + box[2]) / 2, (box[1] + box[3]) / 2
        if len(p) <= capacity or depth >= max_depth or not (box[0] < mx < box[2] and box[1] < my < box[3]):
            out.append(box)
            continue
        right, up = p[:, 0] >= mx, p[:, 1] >= my
        for r in (0, 1):
            for u in (0, 1):
                q = (mx if r else box[0], my if u else box[1], box[2] if r else mx, box[3] if u else my)
                todo.append((q, p[(right == bool(r)) & (up == bool(u))], depth + 1))
    return _extended(out, points, overflow)


def bsp_cells(points: np.ndarray, capacity: int, overflow: str = "extend") -> Cells:
    """Binary splits of the longer side at its median."""
    out, todo = [], [(_extent(points), points)]
    while todo:
        box, p = todo.pop()
        cut = None
        for k in sorted((0, 1), key=lambda k: box[k] - box[k + 2]):
            if len(p) > capacity:
                m = float(np.median(p[:, k]))
                if box[k] < m < box[k + 2] and (p[:, k] < m).any():
                    cut = (k, m)
                    break
        if cut is None:
            out.append(box)
            continue
        k, m = cut
        low, high = list(box), list(box)
        low[k + 2] = high[k] = m
        todo += [(tuple(low), p[p[:, k] < m]), (tuple(high), p[p[:, k] >= m])]
    return _extended(out, points, overflow)


def str_cells(points: np.ndarray, capacity: int, overflow: str = "extend") -> Cells:
    """Sort-tile slices as cells: x quantiles, then y quantiles within each slice."""
    box = _extent(points)
    n = max(1, -(-len(points) // capacity))
    slices = max(1, int(np.ceil(np.sqrt(n))))

    def edges(v: np.ndarray, lo: float, hi: float, parts: int) -> list[float]:
        inner = np.unique(np.quantile(v, np.arange(1, parts) / parts)) if parts > 1 and len(v) else []
        return [lo, *[float(e) for e in inner if lo < e < hi], hi]

    out = []
    xs = edges(points[:, 0], box[0], box[2], slices)
    for x1, x2 in zip(xs, xs[1:], strict=False):
        p = points[(points[:, 0] >= x1) & (points[:, 0] < x2)]
        ys = edges(p[:, 1], box[1], box[3], max(1, -(-len(p) // capacity)))
        out += [(x1, y1, x2, y2) for y1, y2 in zip(ys, ys[1:], strict=False)]
    return _extended(out, points, overflow)


def fixed_cells(extent: tuple[float, float, float, float], nx: int, ny: int) -> FixedCells:
    xs = np.linspace(extent[0], np.nextafter(extent[2], INF), nx + 1)
    ys = np.linspace(extent[1], np.nextafter(extent[3], INF), ny + 1)
    c = _extended([(xs[i], ys[j], xs[i + 1], ys[j + 1]) for i in range(nx) for j in range(ny)], np.zeros((0, 2)), "extend")
    return FixedCells(c.boxes, False, tuple(map(float, extent)), (nx, ny))


def leaf_cells(boxes: np.ndarray, capacity: int, most: int = 10_000) -> LeafCells:
    """The leaves of an R-tree that sample boxes were inserted into one by one."""
    step = -(-len(boxes) // most)
    b = boxes[::step] if step > 1 else boxes
    if not len(b):
        return LeafCells(np.array([(0.0, 0.0, 1.0, 1.0)]))
    # Inserted in a scattered order: in a sorted one, splits would cut strips.
    b = b[np.argsort((np.arange(len(b)) * 2654435761) % (1 << 32), kind="stable")]
    return LeafCells(r_tree(b, max(2, capacity // max(1, step))).levels[-1][0])


def strips(points: np.ndarray, n: int) -> Cells:
    """Vertical strips of equal sample share, for sweeps along x."""
    inner = np.unique(np.quantile(points[:, 0], np.arange(1, n) / n)) if n > 1 and len(points) else np.zeros(0)
    xs = [-INF, *inner.tolist(), INF]
    return Cells(np.array([(a, -INF, b, INF) for a, b in zip(xs, xs[1:], strict=False)]))


#: Partitioners by name, (sample boxes, capacity in sample rows, overflow) -> Cells; `register_partitioner` adds to them.
PARTITIONERS: dict[str, Callable[[np.ndarray, int, str], Cells]] = {
    "kdb": lambda b, capacity, overflow: kdb_cells(_points_in(b), capacity, overflow),
    "quadtree": lambda b, capacity, overflow: quadtree_cells(_points_in(b), capacity, overflow),
    "bsp": lambda b, capacity, overflow: bsp_cells(_points_in(b), capacity, overflow),
    "str": lambda b, capacity, overflow: str_cells(_points_in(b), capacity, overflow),
    "rtree": lambda b, capacity, overflow: leaf_cells(b, capacity),
}


def register_partitioner(name: str, make: Callable[[np.ndarray, int, str], Cells]) -> None:
    """Adds a partitioner: any callable (sample boxes, capacity, overflow) -> Cells."""
    PARTITIONERS[name] = make


def make_cells(kind: str, sample: Sample, share: float | None = None, overflow: str = "extend") -> Cells:
    if kind not in PARTITIONERS:
        raise ValueError(f"no partitioner {kind}; there are {sorted(PARTITIONERS)}")
    return PARTITIONERS[kind](sample.boxes, max(1, len(sample.boxes) // sample.cells(share)), overflow)


def dealt(df: DataFrame, cells: Cells) -> DataFrame:
    """One row for each cell that a box meets: pid."""

    @F.arrow_udf("array<int>")
    def cells_of(x1: pa.Array, y1: pa.Array, x2: pa.Array, y2: pa.Array) -> pa.Array:
        b = np.column_stack([v.to_numpy(zero_copy_only=False) for v in (x1, y1, x2, y2)])
        i, k = cells.of(b)
        order = np.argsort(i, kind="stable")
        ends = np.concatenate([[0], np.cumsum(np.bincount(i, minlength=len(b)))])
        return pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(k[order].astype(np.int32)))

    return df.select("*", F.explode(cells_of(*BOX)).alias("pid"))


def rebalanced(sample: Sample, cells: Cells, skew: float, rounds: int = 24, most: int = MOST_CELLS) -> Cells:
    """Splits cells that hold `skew` times the geometries of the smallest or more, until none is left that a split eases.

    Loads are those of the sample, so no job is needed. A cell is cut at the median of its sample's centres, along its
    longer side first. Cells with less than half of what the given cells hold on average count as holding that, since
    nearly empty ones ask for no split of others.
    """
    kind = type(cells) if isinstance(cells, LeafCells) else Cells
    boxes, done = cells.boxes, set()
    span = sample.extent()
    half = len(sample.boxes) / max(1, len(boxes)) / 2
    for _ in range(rounds):
        now = kind(boxes, cells.bucket)
        i, k = now.of(sample.boxes)
        n = np.bincount(k[k >= 0], minlength=len(boxes))
        least = max(n[n > 0].min(initial=len(sample.boxes)), half, 4.0)
        heavy = [c for c in np.flatnonzero(n >= skew * least).tolist() if tuple(boxes[c]) not in done]
        if not heavy or len(boxes) + len(heavy) > most:
            break
        order = np.argsort(k, kind="stable")
        sorted_k, points = k[order], sample.points
        out = []
        for c in heavy:
            own = points[i[order[np.searchsorted(sorted_k, c) : np.searchsorted(sorted_k, c, "right")]]]
            b = boxes[c]
            own = own[(own[:, 0] >= b[0]) & (own[:, 0] <= b[2]) & (own[:, 1] >= b[1]) & (own[:, 1] <= b[3])]
            width = [min(b[a + 2], span[a + 2]) - max(b[a], span[a]) for a in (0, 1)]
            for axis in sorted((0, 1), key=lambda a: -width[a]):
                m = float(np.median(own[:, axis])) if len(own) else b[axis]
                if b[axis] < m < b[axis + 2]:
                    low, high = b.copy(), b.copy()
                    low[axis + 2] = high[axis] = m
                    halves = kind(np.array([low, high]))
                    part = sample.boxes[i[order[np.searchsorted(sorted_k, c) : np.searchsorted(sorted_k, c, "right")]]]
                    _, h = halves.of(part)
                    if np.bincount(h[h >= 0], minlength=2).max() < 0.9 * n[c]:  # a cut through long boxes eases nothing
                        out.append((c, low, high))
                        break
            else:
                done.add(tuple(b))
        if not out:
            break
        gone = {c for c, *_ in out}
        boxes = np.array([b for c, b in enumerate(boxes) if c not in gone] + [b for _, *two in out for b in two])
    return kind(boxes, cells.bucket)


def _boxes(t: pa.Table, p: str) -> np.ndarray:
    return np.column_stack([t.column(f"{p}_{c}").to_numpy() for c in BOX]).reshape(-1, 4)


def _blocks(d: DataFrame, side: str, parts: dict[int, tuple[int, int]]) -> DataFrame:
    """Adds part: rows of a full cell go to one block of their own side and meet every block of the other."""
    if not parts:
        return d.withColumn("part", F.lit(0))
    pid = F.col("pid")
    number = lambda k: F.coalesce(F.element_at(F.create_map(*(F.lit(x) for c, v in parts.items() for x in (c, v[k]))), pid), F.lit(1))
    ns, nt = number(0), number(1)
    own = F.pmod(F.xxhash64("gid", F.lit(5)), ns if side == "s" else nt).cast("int")
    other = F.sequence(F.lit(0), (nt if side == "s" else ns) - 1)
    part = F.transform(other, lambda o: own * nt + o) if side == "s" else F.transform(other, lambda o: o * nt + own)
    return d.select("*", F.explode(part).alias("part"))


def join_cells(source: DataFrame, target: DataFrame, cells: Cells, local: str = "nested", capacity: int = 16, tile: tuple[float, float] | None = None, sample: Sample | None = None, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """(sid, tid): boxes meet; each pair once, found in the cell of its reference point.

    With a sample, cells that hold more rows than two blocks are joined block by block: a task holds about block_rows of each side.
    """

    find = local_of(local)

    def run(key: tuple[pa.Scalar, ...], left: pa.Table, right: pa.Table) -> pa.Table:
        s, t = _boxes(left, "s"), _boxes(right, "t")
        i, j = find(s, t, capacity, tile)
        own = cells.owns(key[0].as_py(), np.maximum(s[i, 0], t[j, 0]), np.minimum(s[i, 3], t[j, 3]))
        return pa.table({"sid": left.column("sid").to_numpy()[i[own]], "tid": right.column("tid").to_numpy()[j[own]]})

    parts: dict[int, tuple[int, int]] = {}
    if sample and sample.rows:
        share = sample.source.rows / sample.rows
        for c, n in sample.load(cells).items():
            ns, nt = -(-int(n * share) // block_rows), -(-int(n * (1 - share)) // block_rows)
            if n > 2 * block_rows:
                parts[c] = (max(1, ns), max(1, nt))
    columns = (*BOX, "pid", "part")
    s = prefixed(_blocks(dealt(source.select("gid", *BOX), cells), "s", parts).select("gid", *columns), "s", columns)
    t = prefixed(_blocks(dealt(target.select("gid", *BOX), cells), "t", parts).select("gid", *columns), "t", columns)
    return s.groupBy("s_pid", "s_part").cogroup(t.groupBy("t_pid", "t_part")).applyInArrow(run, "sid long, tid long")


def _index_bytes(index) -> int:
    return index.nbytes() + index.items.nbytes


def broadcast_index(source: DataFrame, target: DataFrame, build: Callable[[np.ndarray], object], limit: int = BROADCAST_BYTES) -> DataFrame:
    """(sid, tid) by an index of all source boxes, sent to every task; targets stream past it without a shuffle.

    The limit is checked before the boxes are fetched (by their count) and again on the bytes of the built index.
    """
    spark = source.sparkSession
    n = source.count()
    if n * 40 > limit:
        raise SourceTooLarge(f"{n} source boxes take {n * 40} bytes, over the limit of {limit}")
    got = source.select("gid", *BOX).orderBy("gid").toArrow()
    ids, boxes = got.column(0).to_numpy(), np.column_stack([got.column(k).to_numpy() for k in range(1, 5)]).reshape(-1, 4)
    index = build(boxes)
    if n and ids.nbytes + _index_bytes(index) > limit:
        raise SourceTooLarge(f"an index of {_index_bytes(index)} bytes is over the limit of {limit}")
    shared = spark.sparkContext.broadcast((ids, index))

    def run(batches):
        own, index = shared.value
        for b in batches:
            t = np.column_stack([b.column(k).to_numpy(zero_copy_only=False) for k in range(1, 5)]).reshape(-1, 4)
            i, j = index.query(t)
            yield pa.RecordBatch.from_arrays([pa.array(own[i]), pa.array(b.column(0).to_numpy()[j])], names=["sid", "tid"])

    return target.select("gid", *BOX).mapInArrow(run, "sid long, tid long")


def _strip(column: str, width: float) -> Column:
    return F.floor(F.col(column) / F.lit(width)).cast("long")


def sweep_pairs(source: DataFrame, target: DataFrame, width: float | None = None) -> DataFrame:
    """(sid, tid) by the stops of a plane sweep as an equi-join: every box stops once, in the strip of its xmin, and is
    active in all strips that it reaches into; a pair is found at its later stop (a tie: at the source's), so only once.
    """
    if width is None:
        both = grid.joint(*grid.stats(source, target))
        width = 4 * (both.w or both.h) or 1.0

    def stops(d: DataFrame, p: str) -> DataFrame:
        d = prefixed(d, p, BOX)
        return d.select("*", _strip(f"{p}_xmin", width).alias(f"{p}_strip"))

    def active(d: DataFrame, p: str) -> DataFrame:
        d = prefixed(d, p, BOX)
        return d.select("*", F.explode(F.sequence(_strip(f"{p}_xmin", width), _strip(f"{p}_xmax", width))).alias(f"{p}_strip"))

    same = F.col("s_strip") == F.col("t_strip")
    rows = F.expr("s_ymin <= t_ymax and t_ymin <= s_ymax")
    at_target = active(source, "s").join(stops(target, "t"), same & rows & F.expr("s_xmin < t_xmin and t_xmin <= s_xmax"))
    at_source = stops(source, "s").join(active(target, "t"), same & rows & F.expr("t_xmin <= s_xmin and s_xmin <= t_xmax"))
    return at_target.select("sid", "tid").unionByName(at_source.select("sid", "tid"))


def stripe_pairs(source: DataFrame, target: DataFrame, width: float | None = None) -> DataFrame:
    """(sid, tid) by vertical stripes of the mean source width: an equi-join on stripes, kept in the first common one."""
    if width is None:
        about = grid.stats(source)[0]
        width = about.w or about.h or 1.0

    def side(d: DataFrame, p: str) -> DataFrame:
        d = prefixed(d, p, BOX)
        k = lambda c: F.floor(F.col(f"{p}_{c}") / F.lit(width)).cast("long")
        return d.select("*", k("xmin").alias(f"{p}_first"), F.explode(F.sequence(k("xmin"), k("xmax"))).alias(f"{p}_stripe"))

    s, t = side(source, "s"), side(target, "t")
    first = F.col("s_stripe") == F.greatest("s_first", "t_first")
    return s.join(t, (F.col("s_stripe") == F.col("t_stripe")) & first & boxes_meet()).select("sid", "tid")


def _blocked(df: DataFrame, prefix: str) -> tuple[DataFrame, DataFrame]:
    """(rows, boxes) of a side as blocks of 2^BRUTE_BITS rows: each row's block, and the box around each block."""
    spark = df.sparkSession
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    d = df.select("gid", *BOX).dropna(subset=list(BOX))
    d = written(d.repartitionByRange(n, "xmin").sortWithinPartitions("xmin").withColumn("block", F.shiftright(F.monotonically_increasing_id(), BRUTE_BITS)))
    rows = prefixed(d, prefix, (*BOX, "block"))
    around = [f(f"{prefix}_{c}").alias(f"{prefix}_{c}") for f, c in ((F.min, "xmin"), (F.min, "ymin"), (F.max, "xmax"), (F.max, "ymax"))]
    return rows, rows.groupBy(f"{prefix}_block").agg(*around)


def brute_pairs(source: DataFrame, target: DataFrame) -> DataFrame:
    """(sid, tid) by comparing boxes one by one with all others, block against block.

    Every block of one side is held against every block of the other. Where the boxes around two blocks are apart, no
    boxes in them meet; all the rest are compared, so the product of the sides is looked at whole, whatever its size.
    """
    (s, around_s), (t, around_t) = _blocked(source, "s"), _blocked(target, "t")
    near = written(around_s.crossJoin(around_t).where(boxes_meet()).select("s_block", "t_block"))
    kinds = ", ".join(f"{k} {d.schema['gid'].dataType.simpleString()}" for k, d in (("sid", source), ("tid", target)))

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        a, b = _boxes(left, "s"), _boxes(right, "t")
        i, j = [], []
        for at in range(0, len(a), 256):
            p = a[at : at + 256, None]
            x, y = np.nonzero((p[..., 0] <= b[:, 2]) & (b[:, 0] <= p[..., 2]) & (p[..., 1] <= b[:, 3]) & (b[:, 1] <= p[..., 3]))
            i.append(x + at)
            j.append(y)
        i, j = (np.concatenate([np.zeros(0, np.int64), *k]) for k in (i, j))
        return pa.table({"sid": left.column("sid").take(pa.array(i)), "tid": right.column("tid").take(pa.array(j))})

    left = near.join(s, "s_block")
    right = near.toDF("u_block", "v_block").join(t, F.col("v_block") == F.col("t_block")).drop("t_block")
    return left.groupBy("s_block", "t_block").cogroup(right.groupBy("u_block", "v_block")).applyInArrow(run, kinds)
