"""Grid filters: tiles by arithmetic, an equi-join on tiles, and the reference point that makes each pair unique.

The box test and the ownership test are part of the join condition, so a candidate leaves the join once, without a
shuffle to remove repeats. Tile sizes come from one aggregate a side or from the user. A geometry that would lie in too
many tiles is dealt to tiles of a coarser level (2^level tiles wide), and tiles that hold very many rows are split.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spatial_links.functions.geometry import BOX, SHAPE, boxes_meet, prefixed

#: A side is put on coarser tiles when its geometries would lie in more tiles than this on average.
MAX_TILES_EACH = 64.0
#: A single geometry goes to a coarser level when it would reach over more tiles than this along an axis.
MAX_SPAN = 8
#: Rows of a tile beyond which it is split, and the share of a side that decides it for large inputs.
HOT_ROWS, HOT_SHARE, HOT_SAMPLE = 200_000, 1e-4, 64


@dataclass(frozen=True)
class Tile:
    w: float
    h: float

    def column(self, x: Column, axis: str) -> Column:
        return F.floor(x / F.lit(self.w if axis == "x" else self.h)).cast("long")


@dataclass(frozen=True)
class Stats:
    """What one aggregate over a side's boxes tells: rows, mean, largest and total sizes, extent."""

    rows: int
    w: float
    h: float
    most_w: float
    most_h: float
    area: float
    extent: tuple[float, float, float, float] | None

    def tile(self) -> Tile:
        """The mean width and height; a zero mean takes the other axis, then extent over root of count."""
        x1, y1, x2, y2 = self.extent or (0.0, 0.0, 0.0, 0.0)
        spare = max(x2 - x1, y2 - y1) / max(1.0, (self.rows or 1) ** 0.5) or 1.0
        return Tile(self.w or self.h or spare, self.h or self.w or spare)


def stats(*sides: DataFrame) -> list[Stats]:
    """Stats of each side, by one job over all of them."""
    rows = None
    for k, d in enumerate(sides):
        d = d.select(F.lit(k).alias("side"), *BOX)
        rows = d if rows is None else rows.unionByName(d)
    w, h = F.expr("xmax - xmin"), F.expr("ymax - ymin")
    found = {r.side: r for r in rows.groupBy("side").agg(F.count(F.lit(1)), F.avg(w), F.avg(h), F.max(w), F.max(h), F.sum(w * h), F.min("xmin"), F.min("ymin"), F.max("xmax"), F.max("ymax")).collect()}
    return [Stats(found[k][1], *found[k][2:7], tuple(found[k][7:11])) if k in found else Stats(0, 0.0, 0.0, 0.0, 0.0, 0.0, None) for k in range(len(sides))]


def joint(*parts: Stats) -> Stats:
    """Stats of several sides together."""
    some = [p for p in parts if p.rows]
    if not some:
        return parts[0]
    n = sum(p.rows for p in some)
    mean = lambda k: sum(getattr(p, k) * p.rows for p in some) / n
    ends = list(zip(*(p.extent for p in some), strict=True))
    return Stats(n, mean("w"), mean("h"), max(p.most_w for p in some), max(p.most_h for p in some), sum(p.area for p in some), (min(ends[0]), min(ends[1]), max(ends[2]), max(ends[3])))


def mean_tile(*sides: DataFrame) -> Tile:
    return joint(*stats(*sides)).tile()


def tiles_each(df: DataFrame, tile: Tile) -> Column:
    """How many tiles a box meets, in closed form."""
    n = lambda a, b, k: tile.column(F.col(b), k) - tile.column(F.col(a), k) + 1
    return n("xmin", "xmax", "x") * n("ymin", "ymax", "y")


def coarsened(tile: Tile, *sides: Stats, most: float = MAX_TILES_EACH) -> Tile:
    """The tile, doubled until no side lies in more than `most` tiles on average."""
    for d in sides:
        while (d.w / tile.w + 1) * (d.h / tile.h + 1) > most:
            tile = Tile(tile.w * (2 if d.w / tile.w >= d.h / tile.h else 1), tile.h * (2 if d.h / tile.h > d.w / tile.w else 1))
    return tile


def guarded(tile: Tile, *sides: DataFrame, most: float = MAX_TILES_EACH) -> Tile:
    return coarsened(tile, *stats(*sides), most=most)


def ranged(df: DataFrame, tile: Tile, prefix: str) -> DataFrame:
    """Adds prefix_x1, x2, y1, y2: the ranges of tiles of boxes in prefix_xmin ..."""
    c = lambda k: F.col(f"{prefix}_{k}")
    return df.select("*", tile.column(c("xmin"), "x").alias(f"{prefix}_x1"), tile.column(c("xmax"), "x").alias(f"{prefix}_x2"), tile.column(c("ymin"), "y").alias(f"{prefix}_y1"), tile.column(c("ymax"), "y").alias(f"{prefix}_y2"))


def dealt(df: DataFrame, prefix: str) -> DataFrame:
    """One row for each tile of a ranged side: tx, ty."""
    d = df.select("*", F.explode(F.sequence(f"{prefix}_x1", f"{prefix}_x2")).alias("tx"))
    return d.select("*", F.explode(F.sequence(f"{prefix}_y1", f"{prefix}_y2")).alias("ty"))


def level_of(prefix: str) -> Column:
    """The level at which a ranged geometry reaches over at most MAX_SPAN tiles (and one) along each axis."""
    reach = F.greatest(F.col(f"{prefix}_x2") - F.col(f"{prefix}_x1"), F.col(f"{prefix}_y2") - F.col(f"{prefix}_y1")) + 1
    return F.when(reach <= MAX_SPAN, 0).otherwise(F.ceil(F.log2(reach / MAX_SPAN))).cast("int")


def top_level(tile: Tile, *sides: Stats) -> int:
    """An upper bound of the levels in use, from the largest boxes."""
    reach = max(max(d.most_w / tile.w, d.most_h / tile.h) for d in sides) + 2
    level = 0
    while reach > MAX_SPAN << level:
        level += 1
    return level


def levels_in_use(df: DataFrame, prefix: str, tile: Tile) -> list[int]:
    """The levels of a side's geometries: an aggregate with a handful of rows."""
    return sorted(r.level for r in ranged(prefixed(df, prefix, BOX), tile, prefix).select(level_of(prefix).alias("level")).distinct().collect())


def dealt_levels(df: DataFrame, prefix: str, levels: list[int]) -> DataFrame:
    """One row for each tile of a ranged side at its own level and at each coarser level in use: level, tx, ty.

    A pair meets at the coarser level of its two geometries, so nothing is dealt to tiles finer than its own.
    """
    d = df.select("*", level_of(prefix).alias(f"{prefix}_level"))
    own = F.col(f"{prefix}_level")
    d = d.select("*", F.explode(F.filter(F.array(*(F.lit(k) for k in levels)), lambda k: k >= own)).alias("level"))
    shifted = lambda c: F.expr(f"shiftright({prefix}_{c}, level)")
    d = d.select("*", F.explode(F.sequence(shifted("x1"), shifted("x2"))).alias("tx"))
    return d.select("*", F.explode(F.sequence(shifted("y1"), shifted("y2"))).alias("ty"))


def hot_tiles(df: DataFrame, tile: Tile, rows: int, least: int | None = None, every: int = HOT_SAMPLE) -> list[tuple[int, int, int]]:
    """(tx, ty, parts) of the base tiles that hold very many rows of a side, as a hash sample of it shows.

    The sample decides how work is split only; at most 1 / HOT_SHARE tiles can be hot, whatever the input.
    """
    least = least or max(HOT_ROWS, int(rows * HOT_SHARE))
    if rows <= least:
        return []
    d = df.select("gid", *BOX).where(F.pmod(F.xxhash64("gid", F.lit(17)), F.lit(every)) == 0)
    n = dealt(ranged(prefixed(d, "h", BOX), tile, "h"), "h").groupBy("tx", "ty").agg((F.count(F.lit(1)) * every).alias("n"))
    return [(r.tx, r.ty, -(-r.n // least)) for r in n.where(F.col("n") > least).collect()]


def owns_pair(levels: bool = False) -> Column:
    """The tile holds the pair's reference point: the larger xmin and the smaller ymax, both copies of box corners."""
    x, y = F.greatest("s_x1", "t_x1"), F.least("s_y2", "t_y2")
    if not levels:
        return (F.col("tx") == x) & (F.col("ty") == y)
    return F.expr("level = greatest(s_level, t_level) and tx = shiftright(greatest(s_x1, t_x1), level) and ty = shiftright(least(s_y2, t_y2), level)")


def columns(carry: bool) -> tuple[str, ...]:
    return (*BOX, "dim", "npoints", *SHAPE) if carry else (*BOX, "npoints")


def _split(d: DataFrame, hot: list[tuple[int, int, int]], key: str, copies: bool) -> DataFrame:
    """Adds part: rows of hot tiles are dealt to its parts by a hash, or copied to each of them; others have part 0."""
    spark = d.sparkSession
    each = F.array(*(F.struct(*(F.lit(v).cast("long").alias(c) for v, c in zip(r, ("hx", "hy", "parts"), strict=True))) for r in hot))
    by = F.broadcast(spark.range(1).select(F.inline(each)))
    d = d.join(by, (F.col("tx") == F.col("hx")) & (F.col("ty") == F.col("hy")), "left").withColumn("parts", F.coalesce("parts", F.lit(1)))
    part = F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)) if copies else F.pmod(F.xxhash64(key), F.col("parts"))
    return d.withColumn("part", part).drop("hx", "hy", "parts")


def join_tiles(source: DataFrame, target: DataFrame, tile: Tile, carry: bool = False, own: bool = True, build: str = "auto", about: tuple[Stats, Stats] | None = None, hot_rows: int | None = None) -> DataFrame:
    """Pairs that share a tile and whose boxes meet, with tile ranges and boxes of both sides.

    own=False leaves the ownership test out: the repeats that the reference point removes. build='broadcast' hints
    the source side, for sizes checked by the caller. about: stats of both sides; with them oversized geometries go to
    coarser levels, and tiles with more than hot_rows targets (default: HOT_ROWS, or a share of all) are split.
    """
    s = ranged(prefixed(source, "s", columns(carry)), tile, "s")
    t = ranged(prefixed(target, "t", columns(carry)), tile, "t")
    on = (F.col("tx") == F.col("ux")) & (F.col("ty") == F.col("uy")) & boxes_meet()
    if own and about and top_level(tile, *about):
        both = sorted({*levels_in_use(source, "s", tile), *levels_in_use(target, "t", tile)})
        s, t = dealt_levels(s, "s", both), dealt_levels(t, "t", both)
        t = t.withColumnsRenamed({"level": "t_at", "tx": "ux", "ty": "uy"})
        out = s.join(t, (F.col("level") == F.col("t_at")) & on & owns_pair(True)).drop("ux", "uy", "t_at", "level", "s_level", "t_level")
        return out.withColumns({"tx": F.greatest("s_x1", "t_x1"), "ty": F.least("s_y2", "t_y2")})  # the owner tile of the finest level, as elsewhere
    s, t = dealt(s, "s"), dealt(t, "t")
    hot = hot_tiles(target, tile, about[1].rows, hot_rows) if own and about and build != "broadcast" else []
    if hot:
        s, t = _split(s, hot, "sid", True), _split(t, hot, "tid", False).withColumnRenamed("part", "t_part")
        on = on & (F.col("part") == F.col("t_part"))
    t = t.withColumnsRenamed({"tx": "ux", "ty": "uy"})
    if build == "broadcast":
        s = F.broadcast(s)
    return s.join(t, on & owns_pair() if own else on).drop("ux", "uy", "part", "t_part")


class TileFilter:
    """A Bloom filter of the tiles that sources meet: targets whose tiles it lacks have no candidate.

    Bits are set by an aggregate (a bitwise or per word of 64), so the driver gets `bits` / 64 words at most.
    """

    HASHES, MOST_BITS = 5, 1 << 27

    def __init__(self, source: DataFrame, tile: Tile, rows: int):
        self.tile = tile
        self.bits = 1 << max(10, min(self.MOST_BITS, 16 * max(1, rows)).bit_length())
        tiles = dealt(ranged(prefixed(source, "s", BOX), tile, "s"), "s").select("tx", "ty")
        words = tiles.select(F.explode(self._places()).alias("place")).select(F.shiftright("place", 6).alias("word"), F.expr("shiftleft(1L, cast(place & 63 as int))").alias("bit")).groupBy("word").agg(F.bit_or("bit").alias("bits")).toArrow()
        self.words = np.zeros(self.bits >> 6, np.uint64)
        self.words[words.column(0).to_numpy()] = words.column(1).to_numpy().view(np.uint64)

    def passed(self, target: DataFrame) -> DataFrame:
        """The targets with a tile that the filter holds (or seems to hold); it is sent to the tasks once."""
        shared = target.sparkSession.sparkContext.broadcast(self.words)

        @F.arrow_udf("boolean")
        def held(places: pa.Array) -> pa.Array:
            p = places.flatten().to_numpy()
            bit = (shared.value[p >> 6] >> (p & 63).astype(np.uint64)) & np.uint64(1)
            return pa.array(bit.reshape(-1, TileFilter.HASHES).all(1))

        t = dealt(ranged(prefixed(target, "t", BOX), self.tile, "t"), "t")
        near = t.select("tid", self._places().alias("places")).where(held("places")).select(F.col("tid").alias("gid"))
        return target.join(near, "gid", "left_semi")

    def _places(self) -> Column:
        return F.array(*(F.pmod(F.xxhash64("tx", "ty", F.lit(k)), F.lit(self.bits)) for k in range(self.HASHES)))


def without_repeats(pairs: DataFrame, policy: str) -> DataFrame:
    """The shuffling ways to remove repeats that the reference point replaces."""
    p = pairs.select("sid", "tid")
    if policy == "distinct":
        return p.distinct()
    if policy == "drop_duplicates":
        return p.dropDuplicates(["sid", "tid"])
    if policy == "group_by":
        return p.groupBy("sid", "tid").agg(F.count(F.lit(1)).alias("times")).select("sid", "tid")
    if policy == "reduce_by_key":
        return p.withColumn("one", F.lit(1)).groupBy("sid", "tid").agg(F.first("one")).select("sid", "tid")
    raise ValueError(policy)


def zorder(x: Column, y: Column, bits: int) -> Column:
    """Interleaves the low bits of two tile numbers, x first, by shifts."""
    out = F.lit(0).cast("long")
    for k in range(bits):
        out = out.bitwiseOR(F.shiftleft(F.shiftright(x, k).bitwiseAND(F.lit(1)), 2 * k + 1)).bitwiseOR(F.shiftleft(F.shiftright(y, k).bitwiseAND(F.lit(1)), 2 * k))
    return out


def zorder_pairs(source: DataFrame, target: DataFrame, precision: int, carry: bool = False) -> DataFrame:
    """Equi-join on the cells of a Z-order curve: 2**precision tiles over the joint extent."""
    both = source.select(*BOX).unionByName(target.select(*BOX)).agg(F.min("xmin"), F.min("ymin"), F.max("xmax"), F.max("ymax")).first()
    if both[0] is None:
        both = (0.0, 0.0, 1.0, 1.0)
    cols, rows = 1 << -(-precision // 2), 1 << (precision // 2)
    w, h = ((both[2] - both[0]) or 1.0) / cols, ((both[3] - both[1]) or 1.0) / rows

    def side(d: DataFrame, p: str) -> DataFrame:
        d = prefixed(d, p, columns(carry))
        cell = lambda k, lo, size, n: F.least(F.floor((F.col(f"{p}_{k}") - lo) / size), F.lit(n - 1)).cast("long")
        d = d.select("*", cell("xmin", both[0], w, cols).alias(f"{p}_x1"), cell("xmax", both[0], w, cols).alias(f"{p}_x2"), cell("ymin", both[1], h, rows).alias(f"{p}_y1"), cell("ymax", both[1], h, rows).alias(f"{p}_y2"))
        d = dealt(d, p)
        return d.withColumn(f"{p}_z", zorder(F.col("tx"), F.col("ty"), -(-precision // 2)))

    s, t = side(source, "s"), side(target, "t").drop("tx", "ty")
    return s.join(t, (F.col("s_z") == F.col("t_z")) & boxes_meet() & owns_pair()).drop("s_z", "t_z")
