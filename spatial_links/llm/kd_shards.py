"""Shards by a K-d tree: nodes are split at distributed weighted medians along their widest metadata dimension.

Each row is a point (size, characters, language, source) weighing its bytes; a node that is one point in all of these is
split along the hash of its texts. A node that is to hold k shards is split on the dimension in which its points spread
widest (the first of them if several do), where the bytes to the left are floor(k/2)/k of its own; its
parts are split on until each is one shard, which then has the target bytes. All nodes of a level are split together, and
the rows with their nodes are written once a level.

A median is found by histograms, digit by digit: ten bits of the coordinate, then the text's hash, then a hash of
doc_id, each narrowed to the bin that holds the median, until the error is a small part of a shard. So equal texts
stay together unless their group is itself too large for that, and then it is cut by doc_id; equal texts of several
languages or sources count as having the first of these. The driver sees at most nodes * dimensions * 1024 sums a pass,
whatever the input. Only DataFrame functions are used. Null texts count as empty (16 bytes), null languages and sources as
empty; rows that are equal in all columns are dealt like any other group, rows without a doc_id too.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spatial_links.llm.common import by_ids, drop, materialise, partitions, small

OVERHEAD_BYTES, DIGIT, TOLERANCE = 16, 10, 0.002
DIMENSIONS = ("size", "characters", "language", "source", "hash")
#: Bits of a point's order along a dimension: coordinate, then 32 of the text's hash; of the second key, by doc_id.
FIRST_BITS, SECOND_BITS = 42, 20


def _scaled(x: Column, least: int, most: int) -> Column:
    import math

    span = math.log(max(most, least + 1) / least)
    return F.least(F.lit(1023), F.floor(F.log(F.greatest(x, F.lit(least)) / F.lit(float(least))) / F.lit(span) * 1023)).cast("long")


def points(docs: DataFrame) -> DataFrame:
    """(doc_id, size, text_crc32, q array of 10-bit coordinates, tie) of docs(doc_id, text, lang, source)."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    crc = lambda c: F.crc32(F.coalesce(F.col(c).cast("string"), F.lit("")) if c in docs.columns else F.lit(""))
    rows = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        (F.octet_length(text) + OVERHEAD_BYTES).cast("long").alias("size"),
        (F.char_length(text) + OVERHEAD_BYTES).cast("long").alias("chars"),
        F.crc32(text).alias("text_crc32"),
        crc("lang").alias("lang"),
        crc("source").alias("source"),
    )
    rows = materialise(rows, "metadata")
    a, b, c, d = (int(x or OVERHEAD_BYTES) for x in rows.agg(F.min("size"), F.max("size"), F.min("chars"), F.max("chars")).first())
    group = ["text_crc32", "size"]
    both = rows.groupBy(*group).agg(F.min("lang").alias("lang0"), F.max("lang").alias("lang1"), F.min("source").alias("source0"), F.max("source").alias("source1"))
    mixed = materialise(both.where("lang0 <> lang1 or source0 <> source1").select(*group, "lang0", "source0"), "mixed", 8)
    rows = by_ids(rows, mixed, group, "left")
    coordinate = lambda c: F.shiftright(F.coalesce(f"{c}0", c), 22)
    q = F.array(_scaled(F.col("size"), a, b), _scaled(F.col("chars"), c, d), coordinate("lang"), coordinate("source"), F.shiftright("text_crc32", 22))
    tie = F.xxhash64(F.coalesce("doc_id", F.lit(0))).bitwiseAND(F.lit((1 << SECOND_BITS) - 1))
    return rows.select("doc_id", "size", "text_crc32", q.alias("q"), tie.alias("tie"))


def widest(spans: dict[int, int]) -> int:
    """The dimension to split: the widest of metadata, the first of equals; the hash only where none spreads."""
    last = len(DIMENSIONS) - 1
    return max((d for d in spans if d < last and spans[d] > 0), key=lambda d: (spans[d], -d), default=last)


def _moved(rows: DataFrame, cuts: list[tuple]) -> DataFrame:
    """Each row's node after the cuts (node, dim, first, second) of a level; a node that is not cut stays."""
    by = F.broadcast(small(rows.sparkSession, cuts, "node long, dim int, first long, second long"))
    key = _key(F.col("dim"))
    right = (key > F.col("first")) | ((key == F.col("first")) & (F.col("tie") >= F.col("second")))
    node = F.when(F.col("dim").isNull(), F.col("node")).otherwise(2 * F.col("node") + right.cast("long"))
    return rows.join(by, "node", "left").select(*[c for c in rows.columns if c != "node"], node.alias("node"))


def _key(dim: Column) -> Column:
    return F.shiftleft(F.element_at("q", dim + 1), 32).bitwiseOR(F.col("text_crc32"))


def split(rows: DataFrame, shards: int, tolerance: float = TOLERANCE) -> tuple[DataFrame, dict[int, int]]:
    """rows with `node`, a leaf of the tree, and the number of each leaf."""
    rows = materialise(rows.withColumn("node", F.lit(1).cast("long")), "level")
    open_ = {1: shards}
    while any(k > 1 for k in open_.values()):
        wide = rows.where(F.col("node").isin([n for n, k in open_.items() if k > 1])).select("node", "size", F.posexplode("q").alias("dim", "q"))
        seen: dict[int, dict[int, dict[int, int]]] = {}
        for r in wide.groupBy("node", "dim", "q").agg(F.sum("size").alias("w")).collect():
            seen.setdefault(r.node, {}).setdefault(r.dim, {})[r.q] = r.w
        state = {}
        for node, dims in seen.items():
            total, k = sum(dims[0].values()), open_[node]
            dim = widest({d: max(v) - min(v) for d, v in dims.items()})
            state[node] = {"dim": dim, "goal": total * (k // 2) / k, "near": tolerance * total / k, "left": 0, "at": 0, "shift": FIRST_BITS, "done": False}
            _narrow(state[node], dims[dim], DIGIT)
        while todo := [n for n, s in state.items() if not s["done"]]:
            _refine(rows, state, todo)
        cuts = [(n, s["dim"], *_threshold(s)) for n, s in state.items()]
        before, rows = rows, materialise(_moved(rows, cuts), "level")
        drop(before)
        after = {}
        for n, k in open_.items():
            if k > 1:  # without rows, all its shards stay empty
                after |= {2 * n: k // 2, 2 * n + 1: k - k // 2}
            else:
                after[n] = k
        open_ = after
    return rows, {n: i for i, n in enumerate(sorted(open_, key=lambda x: format(x, "b")))}


def _narrow(s: dict, sums: dict[int, int], bits: int) -> None:
    """Takes the next digit: bins left of the median go left; stops where an edge is near enough."""
    s["shift"] -= bits
    before, put = s["left"], max(sums)
    for v in sorted(sums):
        if before + sums[v] > s["goal"]:
            put = v
            break
        before += sums[v]
    else:
        put += 1
    s["left"], s["at"] = before, (s["at"] << bits) + put
    here = sums.get(put, 0)
    if s["goal"] - before <= s["near"]:
        s["done"] = True
    elif before + here - s["goal"] <= s["near"]:
        s["done"], s["at"] = True, s["at"] + 1
    elif s["shift"] == -SECOND_BITS:
        s["done"], s["at"] = True, s["at"] + (before + here - s["goal"] < s["goal"] - before)


def _refine(rows: DataFrame, state: dict, todo: list[int]) -> None:
    """One more digit for each node of todo, in one pass."""
    part = []
    for n in todo:
        s = state[n]
        bits = min(DIGIT, s["shift"]) if s["shift"] > 0 else DIGIT
        s["bits"] = bits
        part.append((n, s["dim"], s["at"], s["shift"], bits))
    by = F.broadcast(small(rows.sparkSession, part, "node long, dim int, at long, shift int, bits int"))
    key = _key(F.col("dim"))
    first = F.expr("shift > 0")
    full = F.when(first, F.expr("shiftright(k, shift)")).otherwise(F.expr(f"shiftleft(k, -shift) + shiftright(tie, {SECOND_BITS} + shift)"))
    digit = F.when(first, F.expr("shiftright(k, shift - bits) & (shiftleft(1L, bits) - 1)")).otherwise(F.expr(f"shiftright(tie, {SECOND_BITS} + shift - bits) & (shiftleft(1L, bits) - 1)"))
    hist = rows.join(by, "node").withColumn("k", key).where(full == F.col("at")).groupBy("node", digit.alias("digit")).agg(F.sum("size").alias("w")).collect()
    found: dict[int, dict[int, int]] = {n: {} for n in todo}
    for r in hist:
        found[r.node][r.digit] = r.w
    for n in todo:
        _narrow(state[n], found[n], state[n]["bits"])


def _threshold(s: dict) -> tuple[int, int]:
    """(first, second): a row goes right if its pair of keys is this or more."""
    if s["shift"] >= 0:
        return s["at"] << s["shift"], 0
    first, rest = s["at"] >> -s["shift"], s["at"] & ((1 << -s["shift"]) - 1)
    return first, rest << (SECOND_BITS + s["shift"])


def shard(docs: DataFrame, shards: int = 40) -> DataFrame:
    """(doc_id, size, text_crc32, law, shard, slot, grown_shard) for every row of docs; law is `bytes`."""
    spark = docs.sparkSession
    rows = points(docs)
    rows, leaf = split(rows, shards)
    number = F.broadcast(small(spark, list(leaf.items()), "node long, shard int"))
    width = max(4, partitions(spark))
    rows = rows.join(number, "node").select("doc_id", "size", "text_crc32", "shard", F.pmod(F.xxhash64("doc_id", "text_crc32"), F.lit(width)).cast("int").alias("bucket"))
    rows = materialise(rows, "sharded")
    ahead = Window.partitionBy("shard").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    base = rows.groupBy("shard", "bucket").agg(F.count(F.lit(1)).alias("n")).select("shard", "bucket", F.coalesce(F.sum("n").over(ahead), F.lit(0)).alias("base"))
    own = F.row_number().over(Window.partitionBy("shard", "bucket").orderBy("doc_id", "text_crc32")) - 1
    return rows.withColumn("own", own).join(base, ["shard", "bucket"]).select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("own") + F.col("base")).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
