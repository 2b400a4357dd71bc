"""Packing token pieces into as few sequences as possible: a configuration linear program over the length histogram.

A configuration is a multiset of lengths that fits a sequence. The program wants the fewest configurations that
cover the histogram. Lengths go to at most `CLASSES` classes of equal bytes (a class counts as its longest length). A
knapsack dynamic program prices configurations against the dual weights of the classes and adds those worth more than
they cost; optimistic multiplicative weights solve the program over the configurations found so far, both sides at once,
until the value is within `GAP` of the bound that the dual weights prove (or `OUTER` rounds are over). The solution is
rounded down, its classes become lengths again, and what rounding leaves over is placed by best fit, in the free room of
these sequences first. Where plain best fit alone needs no more sequences (many short pieces), its packing is taken.
Only the histogram (at most `capacity` numbers) reaches the driver, so the cost there is the same for any corpus.

Null and empty texts are one end id. Equal lengths are interchangeable, so ties and repeated rows need no care. Rows that
share a doc_id are separate documents.
"""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spatial_links.llm.common import materialise, partitions
from spatial_links.llm.encode import BLOCK_BYTES, CACHE_ENTRIES, encoder
from spatial_links.llm.textops import blocks

CLASSES, GAP, OUTER, INNER = 48, 0.005, 40, 400
Form = tuple[tuple[int, int], ...]


def _pieces(path: str, end_id: int, capacity: int, entries: int, block_bytes: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(path, end_id, entries)
        for rows, raw, off in blocks(batches, size=block_bytes):
            ids, ends = enc.block(raw, off)
            view, out = memoryview(ids.astype("<u4", copy=False)).cast("B"), []
            for i, a, b in zip(rows.column(0).to_pylist(), ends[:-1].tolist(), ends[1:].tolist(), strict=True):
                for k, at in enumerate(range(a, b, capacity)):
                    to = min(at + capacity, b)
                    out.append((i, k, at - a, to - at, zlib.crc32(view[4 * at : 4 * to])))
            cols = list(zip(*out, strict=True)) or [[]] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()), strict=True)], names=["doc_id", "piece", "start", "length", "ids_crc32"])

    return run


def price(weight: np.ndarray, lengths: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """Knapsack over all capacities: (best value, index of the last length taken or -1 for waste) for each capacity."""
    best, last = np.zeros(capacity + 1), np.full(capacity + 1, -1)
    fits = np.searchsorted(lengths, np.arange(capacity + 1), side="right")
    for c in range(1, capacity + 1):
        k = fits[c]
        best[c] = best[c - 1]
        if k:
            value = weight[:k] + best[c - lengths[:k]]
            j = int(value.argmax())
            if value[j] > best[c]:
                best[c], last[c] = value[j], j
    return best, last


def _filling(last: np.ndarray, lengths: np.ndarray, room: int) -> Counter:
    out: Counter = Counter()
    while room > 0:
        j = last[room]
        if j < 0:
            room -= 1
        else:
            out[int(j)] += 1
            room -= int(lengths[j])
    return out


def _matrix(forms: list[Form], rows: int) -> np.ndarray:
    out = np.zeros((rows, len(forms)))
    for k, form in enumerate(forms):
        for j, a in form:
            out[j, k] = a
    return out


def _play(cover: np.ndarray, times: np.ndarray, weight: np.ndarray, prior: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Optimistic multiplicative weights of the game cover[class, configuration]: configurations raise the least covered
    class, class weights look for it. Returns the last and the mean configuration shares, and the mean class weights."""
    log_z, log_q = np.log(np.maximum(0.9 * weight + 0.1 * prior, 1e-12)), np.log(times)
    step = 2.0 / np.abs(cover).max() ** 0.5
    last_z, last_q = cover @ times, weight @ cover
    mean_z, mean_q = np.zeros(len(weight)), np.zeros(len(times))
    for t in range(INNER):
        z, q = np.exp(log_z - log_z.max()), np.exp(log_q - log_q.max())
        z, q = z / z.sum(), q / q.sum()
        now_z, now_q = cover @ q, z @ cover
        log_z -= step * (2 * now_z - last_z)
        log_q += step * (2 * now_q - last_q)
        last_z, last_q = now_z, now_q
        if 2 * t >= INNER:
            mean_z += z
            mean_q += q
    return q, mean_q / mean_q.sum(), mean_z / mean_z.sum()


@dataclass(frozen=True)
class Program:
    """A solved program: times of each configuration (pairs of class and copies), its value, the bound, dual prices."""

    forms: dict[Form, float]
    value: float
    bound: float
    prices: np.ndarray

    @property
    def gap(self) -> float:
        return self.value / self.bound - 1 if self.bound else 0.0


def fractional(lengths: np.ndarray, need: np.ndarray, capacity: int, gap: float = GAP, outer: int = OUTER) -> Program:
    """The least fractional cover of `need` pieces of each length, to within `gap` of its own lower bound."""
    prior = lengths * need / (lengths @ need)
    size = float(lengths @ need) / capacity
    known: dict[Form, int] = {}
    cover, q, z = np.zeros((len(lengths), 0)), np.zeros(0), prior.copy()
    value, bound, prices, times = np.inf, 0.0, lengths / capacity, np.zeros(0)
    for _ in range(outer):
        y = z / need
        best, last = price(y, lengths, capacity)
        if (now := float(need @ y / best[capacity])) > bound:
            bound, prices = now, y / best[capacity]
        if value <= (1 + gap) * bound:
            break
        new = []
        for j in range(len(lengths)):
            form = _filling(last, lengths, int(capacity - lengths[j]))
            form[j] += 1
            key = tuple(sorted(form.items()))
            if key not in known:
                known[key] = len(known)
                new.append(key)
        cover = np.hstack([cover, _matrix(new, len(lengths)) * size / need[:, None]])
        start = np.full(cover.shape[1], 1.0 / cover.shape[1])
        if len(q):
            start *= 0.1
            start[: len(q)] += 0.9 * q
        q, mean, z = _play(cover, start / start.sum(), z, prior)
        for shares in (q, mean):
            least = (cover @ shares).min()
            if least > 0 and size / least < value:
                value, times = size / least, shares / least * size
    return Program({form: float(times[k]) for form, k in known.items() if k < len(times) and times[k] > 1e-9}, float(value), bound, prices)


def classes(lengths: np.ndarray, need: np.ndarray, most: int = CLASSES) -> np.ndarray:
    """The class of each length (ascending): neighbours of about equal bytes together."""
    if len(lengths) <= most:
        return np.arange(len(lengths))
    mass = np.cumsum(lengths * need)
    return np.unique(np.minimum((mass / mass[-1] * most).astype(np.int64), most - 1), return_inverse=True)[1]


@dataclass(frozen=True)
class Plan:
    """Configurations ((length, copies), ...) with their times, which hold exactly the histogram, and a lower bound on any."""

    forms: list[tuple[Form, int]]
    bound: float
    program: Program | None = None

    @property
    def sequences(self) -> int:
        return sum(k for _, k in self.forms)


def solve(histogram: dict[int, int], capacity: int, gap: float = GAP) -> Plan:
    left = {n: c for n, c in histogram.items() if c > 0}
    full = left.pop(capacity, 0)
    whole = [(((capacity, 1),), full)] if full else []
    if not left:
        return Plan(whole, float(full))
    lengths = np.array(sorted(left))
    need = np.array([left[int(n)] for n in lengths], float)
    of = classes(lengths, need)
    longest = np.array([int(lengths[of == k].max()) for k in range(of.max() + 1)])
    program = fractional(longest, np.bincount(of, weights=need), capacity, gap)
    # The dual weights price the lengths themselves, and so bound any packing of them.
    prices = program.prices[of]
    best, _ = price(prices, lengths, capacity)
    bound = full + max(float(lengths @ need) / capacity, float(need @ prices) / best[capacity])
    forms, rest = _rounded(program.forms, of, lengths, need.astype(np.int64))
    plain = _best_fit(dict(left), capacity)
    packed = _best_fit(rest, capacity, forms)
    chosen = min(packed, plain, key=lambda f: sum(k for _, k in f))
    return Plan(whole + chosen, bound, program)


def _rounded(x: dict[Form, float], of: np.ndarray, lengths: np.ndarray, need: np.ndarray) -> tuple[list[tuple[Form, int]], dict[int, int]]:
    """Whole times of each configuration, its classes taken by lengths that are left (the longest first), and what remains."""
    queue = [[[int(n), int(c)] for n, c in zip(lengths[of == k], need[of == k], strict=True)] for k in range(of.max() + 1)]
    left = np.bincount(of, weights=need).astype(np.int64)
    out: list[tuple[Form, int]] = []
    for form, times in sorted(x.items(), key=lambda e: (-e[1], e[0])):
        k = min(int(times), min(int(left[j]) // a for j, a in form))
        if k < 1:
            continue
        slots_: list[list[list[int]]] = []
        for j, a in form:
            left[j] -= a * k
            for _ in range(a):
                taken, want = [], k
                while want:
                    n, c = queue[j][-1]
                    use = min(c, want)
                    taken.append([n, use])
                    want -= use
                    queue[j][-1][1] -= use
                    if c == use:
                        queue[j].pop()
                slots_.append(taken)
        while slots_[0]:
            run = min(t[0][1] for t in slots_)
            out.append((tuple(sorted(Counter(t[0][0] for t in slots_).items(), reverse=True)), run))
            for t in slots_:
                t[0][1] -= run
                if not t[0][1]:
                    t.pop(0)
    return out, {n: c for q in queue for n, c in q if c}


def configurations(histogram: dict[int, int], capacity: int) -> list[tuple[Form, int]]:
    """[(((length, copies), ...), times), ...] that together hold exactly the histogram."""
    return solve(histogram, capacity).forms


def _best_fit(left: dict[int, int], capacity: int, opened: list[tuple[Form, int]] = ()) -> list[tuple[Form, int]]:
    """Best fit decreasing on counts, into the free room of opened configurations too, each with a multiplicity."""
    room: dict[int, dict[tuple, int]] = {}  # free room -> {configuration: times}
    for form, times in opened:
        at = room.setdefault(capacity - sum(a * m for m, a in form), {})
        at[form] = at.get(form, 0) + times
    for n in sorted(left, reverse=True):
        c = left[n]
        while c:
            free = min((r for r in room if r >= n), default=None)
            if free is None:
                per = capacity // n
                k = c // per
                form, times = (((n, per),), k) if k else (((n, c),), 1)
                used = sum(a * m for m, a in form)
                at = room.setdefault(capacity - used, {})
                at[form] = at.get(form, 0) + times
                c -= times * form[0][1]
                continue
            form, times = room[free].popitem()
            a = min(free // n, c)
            k = min(times, c // a)
            if times > k:
                room[free][form] = times - k
            if not room[free]:
                del room[free]
            at = room.setdefault(free - a * n, {})
            grown = (*form, (n, a))
            at[grown] = at.get(grown, 0) + k
            c -= a * k
    return [(form, times) for forms in room.values() for form, times in forms.items()]


def slots(forms: list) -> tuple[np.ndarray, np.ndarray]:
    """(keys, rows): where the r-th piece of a length goes. Key length * 2^40 + first rank; row (rank, copies, sequence, offset)."""
    seen: Counter = Counter()
    keys, rows, sequence = [], [], 0
    for form, times in forms:
        offset = 0
        for n, a in form:
            keys.append((n << 40) + seen[n])
            rows.append((seen[n], a, sequence, offset))
            seen[n] += a * times
            offset += a * n
        sequence += times
    order = np.argsort(np.array(keys, np.int64), kind="stable")
    return np.array(keys, np.int64)[order], np.array(rows, np.int64).reshape(-1, 4)[order]


def _place(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, rows = shared.value
        for b in batches:
            n, rank = (b.column(b.schema.get_field_index(c)).to_numpy(zero_copy_only=False) for c in ("length", "rank"))
            at = rows[np.searchsorted(keys, (n << 40) + rank, side="right") - 1] if len(n) else np.zeros((0, 4), np.int64)
            k = rank - at[:, 0]
            done = [b.column(i) for i in range(5)]
            yield pa.RecordBatch.from_arrays([*done, pa.array(at[:, 2] + k // at[:, 1]), pa.array(at[:, 3] + k % at[:, 1] * n)], names=[*b.schema.names[:5], "sequence_id", "offset"])

    return run


def pack(docs: DataFrame, vocabulary: str, end_id: int = 0, capacity: int = 2048, entries: int = CACHE_ENTRIES, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32, sequence_id, offset) for every piece of docs(doc_id, text).

    entries, block_bytes: pieces of text that a worker remembers and bytes it encodes together, its memory against its time.
    """
    spark = docs.sparkSession
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    pieces = docs.mapInArrow(_pieces(vocabulary, end_id, capacity, entries, block_bytes), "doc_id long, piece int, start long, length long, ids_crc32 long")
    width = max(4, partitions(spark))
    pieces = materialise(pieces.withColumn("bucket", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(width)).cast("int")), "pieces")
    # Ranks within a length: rows of one length, however many, are dealt over `width` buckets, each with its offset.
    per = pieces.groupBy("length", "bucket").agg(F.count(F.lit(1)).alias("n"))
    ahead = Window.partitionBy("length").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    base = per.select("length", "bucket", F.coalesce(F.sum("n").over(ahead), F.lit(0)).alias("base"))
    histogram = {int(r.length): int(r.n) for r in per.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    shared = spark.sparkContext.broadcast(slots(configurations(histogram, capacity)))
    own = Window.partitionBy("length", "bucket").orderBy("doc_id", "piece", "start")
    ranked = pieces.withColumn("own", F.row_number().over(own) - 1).join(base, ["length", "bucket"])
    ranked = ranked.select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("own") + F.col("base")).cast("long").alias("rank"))
    return ranked.mapInArrow(_place(shared), "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
