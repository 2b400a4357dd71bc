"""Near-duplicate groups: many universal-hash minima, banding, signature verification, exact confirmation on
full shingle sets, and connected components by alternating large-star and small-star.

A document's set holds its distinct `width`-word shingles (one shingle of all words if it has fewer; nothing if
it has none). Two documents are linked if 100 * intersection >= `percent` * union. Null and empty texts have an
empty set and link with nothing. Rows without a doc_id take no part: each stays, without a component. Rows that share a
doc_id are one document with several texts: it is linked with whatever one of them is linked with.

Scale. Documents with the same set become one representative first, by a partial aggregate; sets are the same if their
sizes and two independent 64-bit fingerprints are, which is not confirmed word by word. In a bucket no pair
list is made: every member is compared with a few pivots (mergeable minima, so a bucket with a third of all rows
is no task's burden; buckets and pivots that very many rows ask for are broadcast, their number being bounded by the
rows each must have). After a first run of components only documents of buckets that still hold *different*
components are left: those outside a component meet those in that component's buckets that have a size the threshold
allows, in blocks bounded by rows and shingles, where an index of their rarest shingles finds the pairs to be counted
(prefix filter), so that no link between different texts that banding puts together is lost.
With 28 bands of 4 rows a pair at similarity 0.8 misses all bands with probability 4e-7.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spatial_links.llm import textops as T
from spatial_links.llm.common import BROADCAST_IDS, by_ids, connected_components, drop, join_hot, materialise

BANDS, ROWS = 28, 4
#: Written tables get a file for so many documents.
ROWS_A_FILE = 25_000
#: Documents in a block of those outside a component, and of those in its buckets, and shingles in either.
OUTSIDE_BLOCK, AROUND_BLOCK, BLOCK_SHINGLES = 1024, 4096, 1 << 20
#: Numbers of further texts of one doc_id start here; doc_ids must be smaller.
EXTRA = 1 << 62
_U = np.uint64
#: A linked pair agrees on 80 % of the minima give or take 3.8 %; pairs far below that are not compared in full.
LEAST_AGREEMENT = 0.55


def shingle_sets(raw: np.ndarray, off: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """(hash, document) of the distinct shingles of each document of a block, sorted by document and hash."""
    low = T.LOWER[raw]
    start, end, doc = T.words(low, off)
    h = T.span_hash(low, start, end)
    n_docs = len(off) - 1
    count = np.bincount(doc, minlength=n_docs)
    if not len(h):
        return h, doc
    first = np.cumsum(count) - count
    left = count[doc] - (np.arange(len(h)) - first[doc])  # words from here to the end of the document
    take = np.minimum(count[doc], width)
    at = np.flatnonzero((left >= take) & ((count[doc] >= width) | (np.arange(len(h)) == first[doc])))
    s = T.mix(take[at].astype(np.uint64) + _U(77))
    for k in range(width):
        more = take[at] > k
        s[more] = T.mix(s[more] * _U(0x9E3779B97F4A7C15) + h[at[more] + k])
    d = doc[at]
    order = np.lexsort((s, d))
    s, d = s[order], d[order]
    new = np.ones(len(s), bool)
    new[1:] = (s[1:] != s[:-1]) | (d[1:] != d[:-1])
    return s[new], d[new]


def _signed(x: np.ndarray) -> np.ndarray:
    return np.ascontiguousarray(x).view(np.int64)


def _lists(values: np.ndarray, size: int | np.ndarray, rows: int) -> pa.Array:
    ends = np.arange(rows + 1) * size if np.isscalar(size) else np.concatenate([[0], np.cumsum(size)])
    return pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(values))


def _signatures(width: int, bands: int, rows: int, seed: int):
    k = bands * rows
    rng = np.random.default_rng(seed)
    mul = rng.integers(0, 2**63, k, dtype=np.uint64) * _U(2) + _U(1)
    add = rng.integers(0, 2**63, k, dtype=np.uint64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows_, raw, off in T.blocks(batches):
            n = rows_.num_rows
            s, d = shingle_sets(raw, off, width)
            size = np.bincount(d, minlength=n)
            full = np.flatnonzero(size)
            sig = np.zeros((n, k), np.uint32)
            fa, fb = np.zeros(n, np.uint64), np.zeros(n, np.uint64)
            if len(full):
                at = (np.cumsum(size) - size)[full]
                fa[full] = np.add.reduceat(T.mix(s), at)
                fb[full] = np.bitwise_xor.reduceat(T.mix(s ^ _U(0xABCDEF)), at)
                for j in range(k):
                    v = s * mul[j]
                    v += add[j]
                    v >>= _U(32)
                    sig[full, j] = np.minimum.reduceat(v, at)
            key = np.zeros((n, bands), np.uint64)
            for b in range(bands):
                x = np.full(n, b + 1, np.uint64)
                for r in range(rows):
                    x = T.mix(x * _U(0x9E3779B97F4A7C15) + sig[:, b * rows + r])
                key[:, b] = x
            yield pa.RecordBatch.from_arrays(
                [rows_.column(0).cast(pa.int64()), pa.array(size.astype(np.int64)), pa.array(_signed(fa)), pa.array(_signed(fb)), _lists(sig.view(np.int32).ravel(), k, n), _lists(_signed(key).ravel(), bands, n)],
                names=["doc_id", "n_shingles", "fp_a", "fp_b", "sig", "bands"],
            )

    return run


def _fingerprint(s: np.ndarray, size: np.ndarray, full: np.ndarray) -> np.ndarray:
    out = np.zeros(len(size), np.uint64)
    if len(full):
        out[full] = np.add.reduceat(T.mix(s), (np.cumsum(size) - size)[full])
    return out


def _sets(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows_, raw, off in T.blocks(batches):
            s, d = shingle_sets(raw, off, width)
            size = np.bincount(d, minlength=rows_.num_rows)
            fa = _fingerprint(s, size, np.flatnonzero(size))
            yield pa.RecordBatch.from_arrays([rows_.column(0).cast(pa.int64()), pa.array(_signed(fa)), _lists(_signed(s), size, rows_.num_rows)], names=["doc_id", "fp_a", "shingles"])

    return run


def _sets_of(docs: DataFrame, reps: DataFrame, nodes: DataFrame, width: int, files: int) -> DataFrame:
    """(node, shingles) of these nodes, made of their texts again: no set is kept for all documents."""
    wanted = materialise(reps.select("node", "doc_id", "fp_a").join(nodes.select("node"), "node", "left_semi"), "wanted", files)
    ids = materialise(wanted.select("doc_id").distinct(), "need", files)
    made = by_ids(docs, ids, ["doc_id"], "left_semi").mapInArrow(_sets(width), "doc_id long, fp_a long, shingles array<long>")
    sets = materialise(made.join(wanted, ["doc_id", "fp_a"]).groupBy("node").agg(F.first("shingles").alias("shingles")), "sets", files)
    drop(wanted)
    drop(ids)
    return sets


def _confirmed(docs: DataFrame, reps: DataFrame, pairs: DataFrame, width: int, percent: int, k: int, files: int) -> DataFrame:
    """The pairs (u, v) that are linked: first by agreement of their signatures, then on their full sets."""
    side = lambda d, c, x: d.select(F.col("node").alias(x), F.col(c).alias(f"{c}_{x}"))
    agree = "aggregate(zip_with(sig_u, sig_v, (x, y) -> if(x = y, 1, 0)), 0, (s, x) -> s + x)"
    likely = join_hot(join_hot(pairs, side(reps, "sig", "u"), "u"), side(reps, "sig", "v"), "v", counted=pairs)
    likely = materialise(likely.where(f"{agree} >= {int(LEAST_AGREEMENT * k)}").select("u", "v"), "likely", files)
    need = likely.select(F.explode(F.array("u", "v")).alias("node")).distinct()
    sets = _sets_of(docs, reps, need, width, files)
    both = join_hot(join_hot(likely, side(sets, "shingles", "u"), "u"), side(sets, "shingles", "v"), "v", counted=likely)
    both = both.select("u", "v", F.size("shingles_u").alias("nu"), F.size("shingles_v").alias("nv"), F.expr("size(array_intersect(shingles_u, shingles_v))").alias("c"))
    out = materialise(both.where(f"100 * c >= {percent} * (nu + nv - c)").select("u", "v"), "links", files)
    for t in (likely, sets):
        drop(t)
    return out


def _open(shared: DataFrame, comp: DataFrame) -> DataFrame:
    """(node, n, c, big): members of buckets that hold different components c; big is the bucket's largest."""
    now = shared.select("key", "node", "n").join(comp, "node", "left").select("key", "node", "n", F.coalesce("component", "node").alias("c"))
    per = now.groupBy("key", "c").agg(F.count(F.lit(1)).alias("size"))
    mixed = per.groupBy("key").agg(F.count(F.lit(1)).alias("parts"), F.max(F.struct("size", "c")).alias("most"), F.sum("size").alias("rows")).where("parts > 1")
    return join_hot(now, mixed.select("key", F.col("most.c").alias("big"), F.col("rows")), "key", sizes=mixed).select("node", "n", "c", "big").distinct()


def _compare(percent: int):
    """Links between a block of sets outside a component and a block of sets around it: no pair is made but likely ones."""

    def run(outside: pa.Table, around: pa.Table) -> pa.Table:
        us, vs = [], []
        if outside.num_rows and around.num_rows:
            left, right = _Block(outside, "a"), _Block(around, "b")
            for g in np.intersect1d(left.group, right.group):
                for u, v in _linked(left, left.rows(g), right, right.rows(g), percent):
                    us.append(u)
                    vs.append(v)
        u, v = (np.concatenate(x) if x else np.zeros(0, np.int64) for x in (us, vs))
        return pa.table({"u": pa.array(np.minimum(u, v), pa.int64()), "v": pa.array(np.maximum(u, v), pa.int64())})

    return run


class _Block:
    """Rows of one side: node, c, group (a component with its size class and pair of blocks) and sorted sets."""

    def __init__(self, table: pa.Table, side: str):
        table = table.combine_chunks()
        self.node, self.c, self.group = (table.column(f"{n}_{side}").to_numpy() for n in ("node", "c", "group"))
        sets = table.column(f"shingles_{side}").chunk(0)
        self.off = np.frombuffer(sets.buffers()[1], np.int32)[sets.offset : sets.offset + len(sets) + 1]
        self.values = sets.values.to_numpy()
        self.order = np.argsort(self.group, kind="stable")
        self.sorted = self.group[self.order]

    def rows(self, group: int) -> np.ndarray:
        return self.order[np.searchsorted(self.sorted, group) : np.searchsorted(self.sorted, group, "right")]

    def tokens(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(shingle, place in rows) of all sets of some rows."""
        size = self.off[rows + 1] - self.off[rows]
        first = np.cumsum(size) - size
        at = np.arange(size.sum()) - np.repeat(first, size) + np.repeat(self.off[rows], size)
        return self.values[at], np.repeat(np.arange(len(rows)), size)


def _prefixes(rank: np.ndarray, row: np.ndarray, rows: int, percent: int) -> tuple[np.ndarray, np.ndarray]:
    """(rank, row) of the rarest shingles of each set: a linked pair has one of them in common."""
    order = np.lexsort((rank, row))
    rank, row = rank[order], row[order]
    size = np.bincount(row, minlength=rows)
    place = np.arange(len(row)) - (np.cumsum(size) - size)[row]
    keep = place < (size - -(-size * percent // 100) + 1)[row]
    return rank[keep], row[keep]


def _linked(left: _Block, i: np.ndarray, right: _Block, j: np.ndarray, percent: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Linked pairs of rows i of left and j of right that lie in different components."""
    a, own = left.tokens(i)
    b, of = right.tokens(j)
    values, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    count = np.bincount(at)
    rank = np.empty(len(values), np.int64)
    rank[np.lexsort((values, count))] = np.arange(len(values))
    a, b = rank[at[: len(a)]], rank[at[len(a) :]]
    size_a, size_b = np.bincount(own, minlength=len(i)), np.bincount(of, minlength=len(j))
    key, row = _prefixes(b, of, len(j), percent)
    order = np.argsort(key, kind="stable")
    key, row = key[order], row[order]
    mine, whose = _prefixes(a, own, len(i), percent)
    low, high = np.searchsorted(key, mine), np.searchsorted(key, mine, "right")
    ends = np.searchsorted(whose, np.arange(len(i) + 1))
    first_a, first_b = np.concatenate([[0], np.cumsum(size_a)]), np.concatenate([[0], np.cumsum(size_b)])
    mark = np.zeros(len(values), np.int64)
    for r in range(len(i)):
        spans = [row[x:y] for x, y in zip(low[ends[r] : ends[r + 1]], high[ends[r] : ends[r + 1]], strict=True) if y > x]
        if not spans:
            continue
        near = np.unique(np.concatenate(spans))
        n, m = size_a[r], size_b[near]
        near = near[(100 * np.minimum(n, m) >= percent * np.maximum(n, m)) & (right.c[j[near]] != left.c[i[r]])]
        if not len(near):
            continue
        m = size_b[near]
        mark[a[first_a[r] : first_a[r + 1]]] = 1
        starts = np.cumsum(m) - m
        held = mark[b[np.arange(m.sum()) - np.repeat(starts, m) + np.repeat(first_b[near], m)]]
        common = np.add.reduceat(held, starts)
        mark[a[first_a[r] : first_a[r + 1]]] = 0
        hit = near[100 * common >= percent * (n + m - common)]
        yield np.full(len(hit), left.node[i[r]]), right.node[j[hit]]


def _size_class(n, percent: int):
    """Sets of which one can be linked with the other lie in the same or in neighbouring classes."""
    return F.floor(F.log(F.col(n)) / F.lit(float(np.log(100 / percent))) + F.lit(1e-9)).cast("int")


def _rest(open_: DataFrame, sets: DataFrame, percent: int, files: int) -> DataFrame:
    """Links (u, v) of open nodes in different components: all outside a component against those in its buckets.

    Both are dealt to size classes and there to blocks of bounded rows and shingles; the blocks of one class meet those of
    it and its neighbours, each pair in one task, and only links come out.
    """
    kind = _size_class("n", percent)
    outside = open_.where("c <> big").select("big", "node", "c", "n", kind.alias("class")).distinct()
    around = open_.select("big", "node", "c", "n", F.explode(F.sequence(kind - 1, kind + 1)).alias("class")).distinct()
    parts = lambda d, block, c: d.groupBy("big", "class").agg(F.greatest(F.ceil(F.count(F.lit(1)) / block), F.ceil(F.sum("n") / BLOCK_SHINGLES)).cast("int").alias(c))
    n = materialise(parts(outside, OUTSIDE_BLOCK, "no").join(parts(around, AROUND_BLOCK, "nm"), ["big", "class"]), "blocks", files)
    group = F.xxhash64("big", "class", "i", "j").alias("group")
    # Small components share tasks; the blocks of a large one are spread.
    task = F.when((F.col("no") == 1) & (F.col("nm") == 1), F.pmod(F.xxhash64("big", "class"), F.lit(8 * files))).otherwise(F.col("group")).alias("task")
    part = lambda k: F.pmod(F.xxhash64("node", F.lit(3)), F.col(k)).cast("int")
    each = lambda k: F.explode(F.sequence(F.lit(0), F.col(k) - 1))
    left = join_hot(outside, n, ["big", "class"]).select("*", part("no").alias("i")).select("*", each("nm").alias("j")).select("*", group).select("node", "c", "group", task)
    right = join_hot(around, n, ["big", "class"]).select("*", part("nm").alias("j")).select("*", each("no").alias("i")).select("*", group).select("node", "c", "group", task)
    columns = ("node", "c", "group", "task", "shingles")
    left, right = (d.join(sets, "node").select(*(F.col(c).alias(f"{c}_{k}") for c in columns)) for k, d in (("a", left), ("b", right)))
    found = left.groupBy("task_a").cogroup(right.groupBy("task_b")).applyInArrow(_compare(percent), "u long, v long")
    out = materialise(found.distinct(), "links", files)
    drop(n)
    return out


def _with_files(df: DataFrame, old: DataFrame, files: int) -> DataFrame:
    """df written anew; the table it replaces goes."""
    new = materialise(df, "next", files)
    drop(old)
    return new


def near_duplicates(docs: DataFrame, width: int = 5, percent: int = 80, bands: int = BANDS, rows: int = ROWS, seed: int = 11) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for every row of docs(doc_id, text); other columns are ignored."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    k = bands * rows
    sig = materialise(docs.mapInArrow(_signatures(width, bands, rows, seed), "doc_id long, n_shingles long, fp_a long, fp_b long, sig array<int>, bands array<long>"), "signatures")
    files = max(2, -(-sig.count() // ROWS_A_FILE))
    alike = ["fp_a", "fp_b", "n_shingles"]
    some = sig.where("n_shingles > 0 and doc_id is not null")
    firsts = materialise(some.groupBy(*alike).agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("copies")), "firsts", files)
    # One row for each distinct set; a doc_id that stands for several sets is a node of its own number for all but one.
    again = Window.partitionBy("rep").orderBy(*alike)
    number = F.lit(EXTRA).bitwiseOR(F.xxhash64("rep", *alike).bitwiseAND(F.lit(EXTRA - 1)))
    twice = firsts.groupBy("rep").agg(F.count(F.lit(1)).alias("sets")).where("sets > 1").select("rep")
    twice = by_ids(firsts, materialise(twice, "twice", files), ["rep"], "left_semi")
    extra = materialise(twice.select("*", F.row_number().over(again).alias("at")).where("at > 1").select(*alike, "rep", number.alias("node")), "extra", files)
    firsts = firsts.join(F.broadcast(extra) if extra.count() <= BROADCAST_IDS else extra, [*alike, "rep"], "left").withColumn("node", F.coalesce("node", "rep"))
    member = materialise(join_hot(some.select("doc_id", *alike), firsts, alike, sizes=firsts.withColumnRenamed("copies", "rows")).select("doc_id", "n_shingles", "node"), "members", files)
    reps = some.join(firsts.select(*alike, F.col("rep").alias("doc_id"), "node"), [*alike, "doc_id"]).dropDuplicates(["node"])
    reps = materialise(reps.select("node", "doc_id", "fp_a", "n_shingles", "sig", "bands"), "reps", files)

    held = reps.select("node", F.col("n_shingles").alias("n"), F.explode("bands").alias("key"))
    me = F.struct("node", "n")
    hubs = (
        held.groupBy("key")
        .agg(F.count(F.lit(1)).alias("rows"), F.min(me).alias("p0"), F.min(F.struct(F.xxhash64("node").alias("h"), me.alias("p"))).alias("p1"), F.max(F.struct("n", "node")).alias("p2"))
        .where("rows > 1")
        .select("key", "rows", F.array("p0", F.col("p1.p"), F.struct(F.col("p2.node"), F.col("p2.n"))).alias("hubs"))
    )
    hubs = materialise(hubs, "hubs", files)
    shared = materialise(join_hot(held, hubs, "key", sizes=hubs).drop("rows"), "buckets", files)
    near = f"100 * least(n, m) >= {percent} * greatest(n, m)"
    star = (
        shared.select("node", "n", F.explode(F.array_distinct("hubs")).alias("hub"))
        .select("node", "n", F.col("hub.node").alias("other"), F.col("hub.n").alias("m"))
        .where(f"node <> other and {near}")
        .select(F.least("node", "other").alias("u"), F.greatest("node", "other").alias("v"))
        .distinct()
    )
    star = materialise(star, "star", files)
    links = _confirmed(docs, reps, star, width, percent, k, files)
    links = links.unionByName(extra.select(F.col("rep").alias("u"), F.col("node").alias("v")))
    links = links.unionByName(_of_one_id(member))
    comp = materialise(connected_components(links, files), "components", files)
    open_ = materialise(_open(shared, comp), "open", files)
    sets = _sets_of(docs, reps, open_.select("node").distinct(), width, files)
    more = _rest(open_, sets, percent, files)
    comp = _with_files(connected_components(links.unionByName(more), files), comp, files)
    out = join_hot(member, comp, "node", how="left")
    # The component's smallest node is its smallest document: each node is the smallest document of its copies.
    out = materialise(out.select("doc_id", "n_shingles", F.coalesce("component", "node").alias("component_id")), "result", files)
    for t in (reps, hubs, shared, star, more, open_, sets, extra, comp, member):
        drop(t)
    lone = sig.where("n_shingles = 0 or doc_id is null").select("doc_id", "n_shingles", F.col("doc_id").alias("component_id"))
    # A row without text of a document that has other texts is in that document's component.
    lone = lone.join(_blank_ids(lone, out), "doc_id", "left").select("doc_id", "n_shingles", F.coalesce("known", "component_id").alias("component_id"))
    return out.unionByName(lone).select("*", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)).alias("kept"))


def _of_one_id(member: DataFrame) -> DataFrame:
    """Links between the nodes that one doc_id's texts belong to."""
    n = member.groupBy("doc_id").agg(F.min("node").alias("u"), F.max("node").alias("v"), F.count(F.lit(1)).alias("n"))
    some = n.where("u < v").select("doc_id", "u")
    return member.join(some, "doc_id").where("node > u").select("u", F.col("node").alias("v")).distinct()


def _blank_ids(lone: DataFrame, out: DataFrame) -> DataFrame:
    """(doc_id, known): components of doc_ids that have rows with and without words."""
    ids = materialise(lone.where("doc_id is not null").select("doc_id").distinct(), "blank", 2)
    return by_ids(out, ids, ["doc_id"], "left_semi").groupBy("doc_id").agg(F.min("component_id").alias("known"))
