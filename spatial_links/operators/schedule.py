"""Schedulers: which candidates are verified within a budget, and in which order.

Every order is total: weight, then the second scheme, then sid and tid. Positions are given without a window over all
rows in one task: rows are range-partitioned by the whole order, sorted in their partition, written once, and numbered
behind the counts of the partitions before, so equal weights do not meet in one task.
"""

from __future__ import annotations

import heapq
import math
import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spatial_links.plans.shared import dropped, written

#: Pairs that one task puts in dynamic order; more are parted by the components of their geometries.
DYNAMIC_ROWS = 2_000_000


@dataclass(frozen=True)
class Budget:
    """A limit on pairs, on their share of all candidates, or on seconds of verification (see `verified_within`)."""

    max_pairs: int | None = None
    fraction: float | None = None
    max_seconds: float | None = None

    def pairs(self, candidates: int) -> int:
        if self.max_pairs is not None:
            return min(self.max_pairs, candidates)
        return candidates if self.fraction is None else math.ceil(self.fraction * candidates)


BEST = (F.desc, "weight"), (F.desc, "second"), (F.asc, "sid"), (F.asc, "tid")


def best_first() -> list[Column]:
    return [f(c) for f, c in BEST]


def numbered(df: DataFrame, order: list[Column], upto: int | None = None, lead: str | None = None, keep: tuple[str, ...] | None = None) -> DataFrame:
    """Adds position (from 1) in the given total order; rows over `upto` go. keep: the columns to write (none: all).

    lead: the first column of the order, a descending number: with it, rows far below the budget are cut off by an
    approximate quantile (which keeps more than `upto` by its error bound) before any are moved.
    """
    spark = df.sparkSession
    if upto is not None and lead is not None:
        n = df.count()
        if n > 1.2 * upto:
            least = df.approxQuantile(lead, [max(0.0, 1 - upto / n - 0.02)], 0.01)
            df = df.where(F.col(lead) >= least[0])
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    table = written(df.repartitionByRange(parts, *order).sortWithinPartitions(*order).select(*(keep or df.columns), F.monotonically_increasing_id().alias("position")))
    part, rank = F.shiftright("position", 33), F.col("position").bitwiseAND(F.lit((1 << 33) - 1))
    before, base = 0, []
    for r in table.groupBy(part.alias("part")).agg(F.count(F.lit(1)).alias("n")).orderBy("part").collect():
        base += [F.lit(r.part), F.lit(before)]
        before += r.n
    if not base:
        return table
    out = table.withColumn("position", F.element_at(F.create_map(*base), part).cast("long") + rank + 1)
    return out if upto is None else out.where(F.col("position") <= upto)


def global_top(scored: DataFrame, budget: int, keep: tuple[str, ...] | None = None) -> DataFrame:
    """The best `budget` pairs, best first."""
    return numbered(scored, best_first(), budget, "weight", keep)


def _ends(scored: DataFrame, side: str) -> DataFrame:
    """Rows by the geometry that represents them: gid with its side."""
    one = lambda s: scored.select("*", F.lit(s).alias("side"), F.col("sid" if s == "source" else "tid").alias("geo"))
    return one("source").unionByName(one("target")) if side == "both" else one(side)


def local_top(scored: DataFrame, budget: int, side: str = "target", quota: int | None = None) -> DataFrame:
    """A quota of best pairs for each geometry of a side, then the best `budget` of those."""
    ends = _ends(scored, side)
    if quota is None:
        quota = max(1, -(-budget // max(1, ends.select("side", "geo").distinct().count())))
    rank = F.row_number().over(Window.partitionBy("side", "geo").orderBy(*best_first()))
    kept = ends.withColumn("rank", rank).where(F.col("rank") <= quota).select("sid", "tid", "weight", "second")
    return global_top(kept.distinct() if side == "both" else kept, budget)


def with_means(scored: DataFrame, side: str = "target") -> DataFrame:
    """Each pair beside the mean weight of its geometry (rounded, so that no order of summing shows): mean, n, geo, side."""
    ends = _ends(scored, side)
    means = ends.groupBy("side", "geo").agg(F.round(F.avg("weight"), 9).alias("mean"), F.count(F.lit(1)).alias("n"))
    return ends.join(means, ["side", "geo"])


def geometry_ordered(scored: DataFrame, budget: int, side: str = "target") -> DataFrame:
    """Pairs of the geometries of highest mean weight, until the budget; those then by weight."""
    rows = with_means(scored, side)
    if side == "both":  # a pair counts where its geometry ranks higher
        rows = rows.groupBy("sid", "tid", "weight", "second").agg(F.max(F.struct("mean", "side", "geo")).alias("g")).select("sid", "tid", "weight", "second", "g.mean", "g.side", "g.geo")
    chosen = numbered(rows, [F.desc("mean"), F.asc("side"), F.asc("geo"), *best_first()], budget, "mean")
    return global_top(chosen.select("sid", "tid", "weight", "second"), budget)


def round_robin(scored: DataFrame, budget: int, side: str = "target") -> DataFrame:
    """Round i takes each geometry's i-th best pair, geometries in order of their mean weight."""
    rows = with_means(scored, side)
    rows = rows.withColumn("round", F.row_number().over(Window.partitionBy("side", "geo").orderBy(*best_first())))
    rows = rows.withColumn("turn", -F.col("round").cast("double"))
    if side == "both":
        rows = rows.groupBy("sid", "tid", "weight", "second").agg(F.max(F.struct("turn", "mean", "side", "geo")).alias("g")).select("sid", "tid", "weight", "second", "g.turn", "g.mean", "g.side", "g.geo")
    return numbered(rows, [F.desc("turn"), F.desc("mean"), F.asc("side"), F.asc("geo"), F.asc("sid"), F.asc("tid")], budget).select("sid", "tid", "weight", "second", "position")


def tile_ordered(scored: DataFrame, budget: int, tile_order: str = "asc") -> DataFrame:
    """Tiles by how many pairs they own, then pairs of a tile by weight. scored: with the owner tile tx, ty."""
    count = scored.groupBy("tx", "ty").agg(F.count(F.lit(1)).alias("tile_pairs"))
    sign = -1.0 if tile_order == "asc" else 1.0
    rows = scored.join(count, ["tx", "ty"]).withColumn("lead", F.lit(sign) * F.col("tile_pairs"))
    return numbered(rows, [F.desc("lead"), F.asc("tx"), F.asc("ty"), *best_first()], budget).select("sid", "tid", "weight", "second", "position")


def unordered(scored: DataFrame, budget: int, seed: int = 0, keep: tuple[str, ...] = ("sid", "tid", "weight", "second")) -> DataFrame:
    """The batch order as a baseline: by a mixing function of the ids."""
    key = F.pmod(F.col("sid") * 2654435761 + F.col("tid") * 40503 + F.lit(seed), F.lit(1000003))
    rows = scored.withColumn("lead", -key.cast("double"))
    return numbered(rows, [F.desc("lead"), F.asc("sid"), F.asc("tid")], budget, "lead", keep)


def ideal(scored: DataFrame, related: DataFrame | None, budget: int, keep: tuple[str, ...] = ("sid", "tid", "weight", "second")) -> DataFrame:
    """All related pairs first. related: (sid, tid, related boolean), or a column of scored; needs every matrix, so for evaluation only."""
    rows = scored if related is None else scored.join(related.select("sid", "tid", "related"), ["sid", "tid"])
    return numbered(rows.withColumn("lead", F.col("related").cast("double")), [F.desc("lead"), F.asc("sid"), F.asc("tid")], budget, keep=keep)


#: Schedulers by name, (scored pairs with their owner tile, budget) -> positions; `register_scheduler` adds to them.
SCHEDULERS: dict[str, Callable[[DataFrame, int], DataFrame]] = {
    "global": global_top, "local": local_top, "geometry": geometry_ordered, "round_robin": round_robin, "tiles": tile_ordered,
    "tiles_desc": lambda scored, budget: tile_ordered(scored, budget, "desc"), "unordered": unordered,
}


def register_scheduler(name: str, order: Callable[[DataFrame, int], DataFrame]) -> None:
    """Adds a scheduler: any callable (scored, budget) -> the chosen rows with their position."""
    SCHEDULERS[name] = order


def scheduler(name: str) -> Callable[[DataFrame, int], DataFrame]:
    if name not in SCHEDULERS:
        raise ValueError(f"no scheduler {name}; there are {sorted(SCHEDULERS)}")
    return SCHEDULERS[name]


def dynamic_order(rows: list[tuple], boost: float = 1.0, mode: str = "mul") -> list[int]:
    """The order in which (sid, tid, weight, second, related) rows are examined if each related pair found raises the
    weights of the unprocessed pairs that share a geometry with it."""
    if not rows:
        return []
    s, t, w, v, r = zip(*rows, strict=True)
    return dynamic_positions(*(np.asarray(x) for x in (s, t)), np.asarray(w, float), np.asarray(v, float), np.asarray(r, bool), boost, mode)[0].tolist()


def _members(codes: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(starts, rows): the rows of each code, one after another."""
    starts = np.zeros(n + 1, np.int64)
    np.cumsum(np.bincount(codes, minlength=n), out=starts[1:])
    return starts, np.argsort(codes, kind="stable").astype(np.int32)


def dynamic_positions(sid: np.ndarray, tid: np.ndarray, weight: np.ndarray, second: np.ndarray, related: np.ndarray, boost: float = 1.0, mode: str = "mul", worst: bool = True) -> tuple[np.ndarray, np.ndarray | None, np.ndarray]:
    """(order, worst, key): rows in dynamic order; for each place of it the place of the worst key so far (if asked for);
    the keys.

    Only related pairs raise others, so they alone are taken one by one (`_related_in_turn`); where the others come
    between them follows from the keys of those, for all at once (`_between`). What is kept for a row is a few numbers
    in flat arrays.
    """
    n = len(sid)
    rank = np.empty(n, np.int32)  # the order that decides between equal weights
    rank[np.lexsort((tid, sid, -second))] = np.arange(n, dtype=np.int32)
    weight = np.where(np.isnan(weight), -np.inf, weight)
    s_code, t_code = _codes(sid), _codes(tid)
    hit = np.flatnonzero(related).astype(np.int32) if boost else np.zeros(0, np.int32)
    rest = np.ones(n, bool)
    rest[hit] = False
    taken, taken_key = _related_in_turn(s_code, t_code, weight, rank, hit, boost, mode == "add")
    place, key = np.empty(n, np.int32), np.empty(n)
    place[taken], key[taken] = np.arange(len(taken), dtype=np.int32), taken_key
    rest = np.flatnonzero(rest).astype(np.int32)
    for at, where, k in _between(s_code, t_code, weight, rank, rest, taken, taken_key, boost, mode == "add"):
        place[at], key[at] = where, k
    del s_code, t_code, weight, rest, taken_key, hit
    last = np.zeros(n, bool)
    last[taken] = True  # what comes before the same related pair is in the order of its keys
    del taken
    out = np.lexsort((rank, -key, last, place)).astype(np.int32)
    del place, last
    key = key[out]
    if not worst:
        return out, None, key
    by = np.lexsort((rank[out], -key))
    place = np.empty(n, np.int64)
    place[by] = np.arange(n)
    return out, by[np.maximum.accumulate(place)], key


def _codes(ids: np.ndarray) -> np.ndarray:
    return np.searchsorted(np.unique(ids), ids).astype(np.int32)


def _related_in_turn(s_code: np.ndarray, t_code: np.ndarray, weight: np.ndarray, rank: np.ndarray, hit: np.ndarray, boost: float, add: bool) -> tuple[np.ndarray, np.ndarray]:
    """(rows, keys) of the related rows `hit`, in the order in which they are taken.

    Each source geometry has its best pair at hand, and a heap these only, each as (-key, rank of its ties, pair). A pair
    taken has the pairs of its source compared anew, and those of its target with the best of their sources. Entries that
    are no longer a source's best are passed over, and thrown out once they are most of the heap.
    """
    hit = hit[np.argsort(s_code[hit], kind="stable")]
    s, t = _codes(s_code[hit]), _codes(t_code[hit])
    m, sources, targets = len(hit), int(s.max(initial=-1)) + 1, int(t.max(initial=-1)) + 1
    s_at, (t_at, t_rows) = np.searchsorted(s, np.arange(sources + 1)), _members(t, targets)
    out, key = np.empty(m, np.int32), np.empty(m)
    W, RANK, SC, TC, SA, TA, TR, OUT, K = (memoryview(np.ascontiguousarray(x)) for x in (weight[hit], rank[hit], s, t, s_at, t_at, t_rows, out, key))
    done, hits_s, hits_t = bytearray(m), [0] * sources, [0] * targets
    best, best_key, none = [-1] * sources, [0.0] * sources, len(weight)
    most = int(np.diff(s_at).max(initial=0) + np.diff(t_at).max(initial=0)) + 1
    raised = [boost * h if add else 1 + boost * h for h in range(most)]  # what h hits add to a weight, or multiply it by
    heap: list[tuple[float, int, int]] = []
    push, pop = heapq.heappush, heapq.heappop

    def choose(a: int) -> None:
        """The best of a source's pairs that are left."""
        by, top, at, tie, k, end = raised[hits_s[a] :], -math.inf, -1, none, SA[a], SA[a + 1]
        for left, w, b in zip(done[k:end], W[k:end], TC[k:end]):  # noqa: B905
            if not left:
                x = w + by[hits_t[b]] if add else w * by[hits_t[b]]
                if x >= top and (x > top or RANK[k] < tie):
                    top, at, tie = x, k, RANK[k]
            k += 1
        best[a], best_key[a] = at, top
        if at >= 0:
            push(heap, (-top, tie, at))

    for a in range(sources):
        choose(a)
    for place in range(m):
        x, _, i = pop(heap)
        while best[SC[i]] != i or best_key[SC[i]] != -x:
            x, _, i = pop(heap)
        a, b = SC[i], TC[i]
        done[i] = 1
        OUT[place], K[place] = i, -x
        hits_s[a] += 1
        hits_t[b] += 1
        choose(a)
        by = raised[hits_t[b] :]
        for k in TR[TA[b] : TA[b + 1]]:
            if done[k]:
                continue
            c = SC[k]
            x = W[k] + by[hits_s[c]] if add else W[k] * by[hits_s[c]]
            top = best_key[c]
            if x < top:
                if best[c] == k:
                    choose(c)
            elif x > top or best[c] != k and RANK[k] < RANK[best[c]]:
                best[c], best_key[c] = k, x
                push(heap, (-x, RANK[k], k))
        if len(heap) > 2 * sources + 100_000:
            heap[:] = [(-best_key[c], RANK[k], k) for c, k in enumerate(best) if k >= 0]
            heapq.heapify(heap)
    return hit[out], key


def _between(s_code: np.ndarray, t_code: np.ndarray, weight: np.ndarray, rank: np.ndarray, rest: np.ndarray, taken: np.ndarray, taken_key: np.ndarray, boost: float, add: bool) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(rows, place, key) of the rows `rest`, some at a time: the first related row of `taken` whose key is worse, or its end.

    A row's key is raised after each related row that shares a geometry with it. So from one such row to the next it is
    the same, and the first worse key is found by halves in a table of the worst of 1, 2, 4 ... places.
    """
    m = len(taken)
    if not m or not len(rest):
        yield rest, np.full(len(rest), m), weight[rest]
        return
    # The places of keys from the best to the worst, ties by rank; the worst of each block of 2^k places.
    by = np.lexsort((rank[taken], -taken_key))
    worth, sorted_key, sorted_rank = np.empty(m, np.int32), -taken_key[by], rank[taken][by]
    worth[by] = np.arange(m, dtype=np.int32)
    blocks = [worth]
    while len(blocks[-1]) > 1:
        v = blocks[-1]
        blocks.append(np.maximum(v[0::2], np.append(v[1::2], v[-1:] if len(v) % 2 else v[:0])))

    size = np.array([len(v) for v in blocks])
    flat, base = np.concatenate(blocks), np.cumsum(size) - size
    del blocks

    def better(x: np.ndarray, r: np.ndarray) -> np.ndarray:
        """How many keys are better than each x with its rank r."""
        low, high = np.searchsorted(sorted_key, -x, "left"), np.searchsorted(sorted_key, -x, "right")
        tied = np.flatnonzero(low < high)
        lo, hi, own = low[tied], high[tied], r[tied]
        while (lo < hi).any():
            mid = (lo + hi) // 2
            up = (lo < hi) & (sorted_rank[np.minimum(mid, m - 1)] < own)
            lo, hi = np.where(up, mid + 1, lo), np.where(up | (lo >= hi), hi, mid)
        low[tied] = lo
        return low

    def first_from(start: np.ndarray, least: np.ndarray) -> np.ndarray:
        """The first place from start on whose worth is at least `least`; m without one."""
        out, open_ = np.full(len(start), m, np.int64), np.flatnonzero(start < m)
        a, k, least = start[open_], np.zeros(len(open_), np.int64), least[open_]
        while len(open_):
            holds = flat[base[k] + a] >= least
            found = holds & (k == 0)
            out[open_[found]] = a[found]
            up = ~holds & (a % 2 == 1)  # the next block begins one of twice the size
            a, k = np.where(holds, 2 * a, np.where(up, (a + 1) // 2, a + 1)), k - holds + up
            left = ~found & (k < len(size))
            left &= a < size[np.clip(k, 0, len(size) - 1)]
            open_, a, k, least = open_[left], a[left], k[left], least[left]
        return out

    # The places of each geometry's related rows.
    (s_at, s_places), (t_at, t_places) = (_members(c[taken], int(c.max()) + 1) for c in (s_code, t_code))
    for rows in np.array_split(rest, -(-len(rest) // 100_000)):
        place, key = np.empty(len(rows), np.int64), np.empty(len(rows))
        a, a_end, b, b_end = s_at[s_code[rows]], s_at[s_code[rows] + 1], t_at[t_code[rows]], t_at[t_code[rows] + 1]
        start, h, open_ = np.zeros(len(rows), np.int64), np.zeros(len(rows), np.int64), np.arange(len(rows))
        while len(open_):
            w, r = weight[rows[open_]], rank[rows[open_]]
            x = w + boost * h if add else w * (1 + boost * h)
            # The next related row of either geometry, after which the key is another.
            one = np.where(a < a_end, s_places[np.minimum(a, m - 1)], m)
            two = np.where(b < b_end, t_places[np.minimum(b, m - 1)], m)
            until = np.minimum(one, two)
            at = first_from(start, better(x, r))
            ends = (at <= until) | (until >= m)
            place[open_[ends]], key[open_[ends]] = at[ends], x[ends]
            go = ~ends
            by_s, by_t = (one == until)[go], (two == until)[go]  # both, if a pair is there more than once
            a, b, h, start = a[go] + by_s, b[go] + by_t, h[go] + by_s + by_t, until[go] + 1
            a_end, b_end, open_ = a_end[go], b_end[go], open_[go]
        yield rows, place, key


def _connected(pairs: DataFrame) -> DataFrame:
    """(geo, part) of the sources (by hash): those that pairs join, over any number of others, have the same part.

    Large and small stars by turns, until no edge changes. Ids of both sides are hashed to one; were two to clash, parts
    would only be larger.
    """
    node = lambda side, c: F.xxhash64(F.lit(side), c)
    a, b = node("source", "sid"), node("target", "tid")
    edges = written(pairs.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct())
    least = F.least("u", F.min("v").over(Window.partitionBy("u")))
    before = None
    while True:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = both.withColumn("m", least).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        small = large.withColumn("m", F.min("v").over(Window.partitionBy("u"))).select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.*")
        new = written(small.where("u <> v").distinct())
        dropped(edges)
        edges, now = new, tuple(new.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("u", "v")), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        if now == before:
            return edges.select(F.col("u").alias("geo"), F.col("v").alias("part"))
        before = now


_TAKEN = ("worst_key", "worst_second", "worst_sid", "worst_tid")


def dynamic_top(verified: DataFrame, boost: float = 1.0, mode: str = "mul", shard: Column | None = None, most: int = DYNAMIC_ROWS, shards: int | None = None) -> DataFrame:
    """(shard, position, sid, tid, weight, second, related) in dynamic order inside each shard.

    verified: the retained pairs (sid, tid, weight, second, related). All of them are examined within the budget, so
    their matrices are computed in parallel first; only the order, which is sequential, is found in one task a shard.

    shards: how many there are, if few and large; they are then dealt to tasks by ranges of even load, smallest number
    first, since by a hash several would meet in one. Without shards, more than `most` pairs are parted by the connected components of their geometries, of which none
    can raise a pair of another. The order of all is the merge of theirs: a pair comes when the worst key that came before
    it in its own part (or its own) is the best at hand. So it is sorted by that key, then by its place in the part.
    """
    schema = "shard int, position long, sid long, tid long, weight double, second double, related boolean"
    parted = shard is None and verified.count() > most
    columns = ("sid", "tid", "weight", "second", "related")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts: list[list[np.ndarray]] = []
        for b in batches:
            number = b.column("shard")[0].as_py()
            parts.append([b.column(c).to_numpy(zero_copy_only=False).copy() for c in columns])
        data = []
        for k in range(len(columns)):  # a column at a time: its batches go once it is whole
            data.append(np.concatenate([p[k] for p in parts]))
            for p in parts:
                p[k] = None
        order, worst, key = dynamic_positions(*data, boost, mode, parted)
        for at in range(0, len(order), 100_000):
            rows = order[at : at + 100_000]
            out = {"shard": np.full(len(rows), number, np.int32), "position": np.arange(at + 1, at + len(rows) + 1), **{c: d[rows] for c, d in zip(columns, data, strict=True)}}
            if parted:
                w = worst[at : at + 100_000]
                out |= dict(zip(_TAKEN, (key[w], *(data[k][order[w]] for k in (3, 0, 1))), strict=True))
            yield pa.RecordBatch.from_pydict({c: pa.array(v) for c, v in out.items()})

    if not parted:
        rows = verified.withColumn("shard", F.lit(0) if shard is None else shard.cast("int"))
        rows = rows.select("shard", *columns)
        return (rows.repartitionByRange(shards, "shard") if shards else rows).groupBy("shard").applyInArrow(run, schema)
    verified = written(verified.select(*columns))
    own = F.xxhash64(F.lit("source"), "sid")
    tasks = int(verified.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = verified.withColumn("geo", own).join(_connected(verified), "geo", "left")
    rows = rows.select(F.pmod(F.xxhash64(F.coalesce("part", "geo")), F.lit(max(tasks, -(-4 * verified.count() // most)))).cast("int").alias("shard"), *columns)
    done = rows.groupBy("shard").applyInArrow(run, f"{schema}, worst_key double, worst_second double, worst_sid long, worst_tid long")
    order = [F.desc("worst_key"), F.desc("worst_second"), F.asc("worst_sid"), F.asc("worst_tid"), F.asc("place")]
    all_ = numbered(done.withColumnRenamed("position", "place"), order)
    return all_.select(F.lit(0).alias("shard"), "position", *columns)


def dynamic_rounds(scored: DataFrame, verify, budget: int, round_size: int, boost: float = 1.0) -> DataFrame:
    """The global form: rounds of `round_size` pairs; after each, weights are recomputed from the hits so far.

    verify: DataFrame(sid, tid) -> DataFrame(sid, tid, related). With round_size 1 the order equals the exact one.
    Between rounds two tables are kept: the pairs not yet examined, and the hits of each geometry; older ones are deleted.
    """
    rest = written(global_top(scored, budget).select("sid", "tid", "weight", "second"))
    out, hits, at = None, None, 0
    total = rest.count()
    while at < total:
        now = rest.withColumn("base", F.col("weight"))
        if hits is not None:
            of = lambda side, key: hits.where(F.col("side") == side).select(F.col("geo").alias(key), F.col("n").alias(f"n_{key}"))
            now = rest.join(of("source", "sid"), "sid", "left").join(of("target", "tid"), "tid", "left")
            n = F.coalesce("n_sid", F.lit(0)) + F.coalesce("n_tid", F.lit(0))
            now = now.select("sid", "tid", (F.col("weight") * (1 + boost * n)).alias("weight"), "second", F.col("weight").alias("base"))
        part = written(numbered(now, best_first(), round_size))
        found = written(verify(part.select("sid", "tid")).join(part, ["sid", "tid"]).select((F.col("position") + at).alias("position"), "sid", "tid", F.col("base").alias("weight"), "second", "related"))
        out = found if out is None else out.unionByName(found)
        left = written(rest.join(part.select("sid", "tid"), ["sid", "tid"], "left_anti"))
        new = _ends(found.where("related"), "both").groupBy("side", "geo").agg(F.count(F.lit(1)).alias("n"))
        more = written(new if hits is None else hits.unionByName(new).groupBy("side", "geo").agg(F.sum("n").alias("n")))
        for old in (rest, part, hits):
            if old is not None:
                dropped(old)
        rest, hits, at = left, more, at + round_size
    return out


def shares(counts: dict[int, int], budget: int) -> dict[int, int]:
    """Splits a budget in proportion to counts; largest remainders get what rounding leaves, so shares add up to it."""
    total = sum(counts.values())
    budget = min(budget, total)
    out = {k: budget * n // total for k, n in counts.items()} if total else {}
    rest = sorted(counts, key=lambda k: (-(budget * counts[k] % total), k)) if total else []
    for k in rest[: budget - sum(out.values())]:
        out[k] += 1
    return out


def tile_shard(shards: int) -> Column:
    """The partition of the distributed grid that owns a pair: its owner tile's."""
    return F.pmod(F.col("tx") * 31 + F.col("ty"), F.lit(shards))


def with_quota(scored: DataFrame, budget: int, shard: Column) -> DataFrame:
    """Adds shard and quota, the shard's part of the budget in proportion to its candidates."""
    rows = scored.withColumn("shard", shard)
    counts = {r.shard: r.n for r in rows.groupBy("shard").agg(F.count(F.lit(1)).alias("n")).collect()}
    quota = shares(counts, budget)
    if not quota:
        return rows.withColumn("quota", F.lit(0).cast("long")).limit(0)
    return rows.withColumn("quota", F.element_at(F.create_map(*(F.lit(x) for k, v in quota.items() for x in (k, v))), F.col("shard")).cast("long"))


def sharded(scored: DataFrame, budget: int, shard: Column, order: str = "global") -> DataFrame:
    """A scheduler within each shard's part of the budget: no global sort. Adds shard and the position in it.

    order: global, local, geometry, round_robin (by target) or tiles; a shard is a partition of the join, whose tiles are
    whole, so there must be enough of them that one task can sort a shard's pairs.
    """
    rows = with_quota(scored, budget, shard)
    at = lambda *by: F.row_number().over(Window.partitionBy("shard").orderBy(*by))
    geo = Window.partitionBy("shard", "tid")
    if order in ("geometry", "round_robin"):
        rows = rows.withColumn("mean", F.round(F.avg("weight").over(geo), 9))
    if order in ("local", "round_robin"):
        rows = rows.withColumn("turn", F.row_number().over(geo.orderBy(*best_first())))
    if order == "local":
        targets = rows.groupBy("shard").agg(F.count_distinct("tid").alias("targets"))
        rows = rows.join(F.broadcast(targets), "shard").where("turn <= greatest(1, cast(ceil(quota / targets) as bigint))")
    if order == "tiles":
        rows = rows.withColumn("tile_pairs", F.count(F.lit(1)).over(Window.partitionBy("shard", "tx", "ty")))
    if order == "geometry":
        rows = rows.withColumn("chosen", at(F.desc("mean"), F.asc("tid"), *best_first())).where("chosen <= quota")
    by = {"round_robin": [F.asc("turn"), F.desc("mean"), F.asc("tid"), F.asc("sid")], "tiles": [F.asc("tile_pairs"), F.asc("tx"), F.asc("ty"), *best_first()]}
    rows = rows.withColumn("position", at(*by.get(order, best_first())).cast("long")).where("position <= quota")
    return rows.select("shard", "position", "sid", "tid", "weight", "second")


def verified_within(ordered: DataFrame, source: DataFrame, target: DataFrame, seconds: float, tasks: int | None = None, step: int = 256) -> DataFrame:
    """Verification under a time budget, run at once: (position, sid, tid, related) of the pairs examined in time.

    Pairs are dealt to tasks by position, so that all work on the best first, and a task looks at the clock before every
    `step` pairs. The deadline is one moment for all tasks; what a task has begun it finishes.
    """
    from spatial_links.operators import verify

    columns = [p + c for p in ("s_", "t_") for c in ("dim", *verify.SHAPE)]
    n = tasks or int(source.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = verify.attach(ordered.select("position", "sid", "tid"), source, target).select("position", "sid", "tid", *columns)
    rows = rows.repartition(n, F.pmod(F.col("position"), F.lit(n))).sortWithinPartitions("position")
    end = time.time() + seconds

    def run(batches):
        for b in batches:
            for at in range(0, b.num_rows, step):
                if time.time() >= end:
                    return
                yield verify.matrix_batch(b.slice(at, step))

    m = written(rows.mapInArrow(run, "position long, sid long, tid long, s_dim tinyint, t_dim tinyint, matrix string"))
    return m.select("position", "sid", "tid", verify.relation("intersects", F.col("matrix"), F.col("s_dim"), F.col("t_dim")).alias("related"))
