"""Benchmark decontamination by template canonicalisation.

A text becomes words in which numbers, units after numbers and names inside sentences are typed placeholders that
keep their value beside them; case and punctuation go. Windows of `window` canonical words of the benchmark are
hash-joined with every `stride`-th window of the documents: any common run of window + stride - 1 words holds such a
window, so none of them is missed. Items of which a shorter run suffices are joined with every window instead. For each pair and alignment found, every run of
equal canonical words of `min_run` words (or the whole item if that is shorter) is judged. Each benchmark value must stand
for one value in the document (a re-parameterised question renames consistently): a run is cut at the slots of values that
stand for several in it. A document leaks an item if a part has that many words, at least half as many not placeholders,
or if that many words are equal with their values, whatever stands around them.

The benchmark's windows are broadcast only below a checked count, else shuffled. Only DataFrame functions are used.
Null and empty texts and items match nothing. Rows equal in doc_id and text give one result; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spatial_links.llm.common import by_ids, materialise, small

WINDOW, STRIDE, MIN_RUN = 8, 5, 12
BROADCAST_WINDOWS = 2_000_000
#: Units that a number may carry.
UNITS = "mm|cm|m|km|inch|inches|feet|miles|mg|g|kg|tons?|ml|l|litres?|liters?|s|sec|seconds?|min|minutes?|h|hours?|days?|weeks?|months?|years?|euros?|dollars?|cents?|percent|degrees?|volts?|watts?|hz|mph|kmh"


def canonical(text: Column) -> Column:
    """Words, placeholders as `#type=value`."""
    x = F.regexp_replace(text, r"[0-9]+(?:[.,:/][0-9]+)*", " #num=$0 ")
    x = F.regexp_replace(x, rf"(#num=\S+) +(?i)({UNITS})(?![\p{{L}}])", "$1 #unit=$2 ")
    x = F.regexp_replace(x, r"(?<=[\p{Ll},;] )\p{Lu}\p{Ll}+", "#name=$0")
    x = F.regexp_replace(F.lower(x), r"[^\p{L}\p{N}#=.,:/]+|(?<![0-9])[.,:/]+|[.,:/]+(?![0-9])", " ")
    return F.array_remove(F.split(x, " +"), "")


def _types(words: Column) -> Column:
    return F.split(F.regexp_replace(F.array_join(words, " "), r"=\S*", ""), " ")


def _windows(words: Column, size: int, stride: int) -> Column:
    last = F.size(words) - size
    at = F.when(last >= 0, F.sequence(F.lit(0), F.greatest(last, F.lit(0)), F.lit(stride))).otherwise(F.array().cast("array<int>"))
    return F.transform(at, lambda i: F.struct(i.alias("at"), F.xxhash64(F.slice(words, i + 1, size)).alias("key")))


def _parts(start: Column, end: Column, breaks: Column) -> Column:
    """The parts of [start, end) between positions `breaks` (ascending), as structs (from, to)."""
    edges = F.concat(F.array(start - 1), breaks, F.array(end))
    return F.zip_with(F.slice(edges, 1, F.size(edges) - 1), F.slice(edges, 2, F.size(edges) - 1), lambda x, y: F.struct((x + 1).alias("from"), y.alias("to")))


def _long(parts: Column) -> Column:
    return F.filter(parts, lambda r: r["to"] - r["from"] >= F.col("least"))


def _pieces(pairs: DataFrame) -> DataFrame:
    """Adds from, run_words, exact: parts of an alignment's runs of equal types that show a leak, of `least` words or more.

    Shown by equal words, or by a part without a slot that the run contradicts and with enough plain words.
    """
    word, shift = F.col("item"), F.col("shift")
    mine = lambda i: F.get("words", i + shift)
    theirs = lambda i: F.get(word, i)
    within = lambda r: F.sequence(r["from"], r["to"] - 1)
    first, end = F.greatest(F.lit(0), -shift), F.least(F.size("item"), F.size("words") - shift)
    unlike = F.filter(F.sequence(first, end - 1), lambda i: F.get("item_types", i) != F.get("types", i + shift))
    keep = ["doc_id", "item_id", "shift", "item", "words", "least"]
    runs = pairs.select(*keep, F.explode(_long(_parts(first, end, unlike))).alias("run"))
    slots = F.array_distinct(F.transform(F.filter(within(F.col("run")), lambda i: theirs(i).startswith("#")), lambda i: F.struct(theirs(i).alias("b"), mine(i).alias("d"))))
    runs = runs.withColumn("slots", F.transform(slots, lambda x: x["b"])).withColumn("names", F.array_distinct("slots"))
    odd = F.when(F.size("slots") == F.size("names"), F.array().cast("array<string>")).otherwise(F.filter("names", lambda b: F.size(F.filter("slots", lambda x: x == b)) > 1))
    runs = runs.withColumn("odd", odd)
    cut = lambda breaks: _long(_parts(F.col("run.from"), F.col("run.to"), breaks))
    equal = F.transform(cut(F.filter(within(F.col("run")), lambda i: theirs(i) != mine(i))), lambda r: F.struct(r["from"].alias("from"), r["to"].alias("to"), F.lit(True).alias("exact")))
    alike = F.transform(cut(F.filter(within(F.col("run")), lambda i: F.array_contains("odd", theirs(i)))), lambda r: F.struct(r["from"].alias("from"), r["to"].alias("to"), F.lit(False).alias("exact")))
    parts = runs.select(*keep, F.explode(F.concat(equal, alike)).alias("part"))
    plain = F.size(F.filter(F.slice("item", F.col("part.from") + 1, F.col("part.to") - F.col("part.from")), lambda w: ~w.startswith("#")))
    parts = parts.withColumn("enough", F.col("part.exact") | (2 * plain >= F.col("part.to") - F.col("part.from")))
    # Of a part with too few plain words, the longest one inside it that has enough: level(i) is plain words less others before i.
    ahead = F.transform(F.sequence(F.col("part.from"), F.col("part.to") - 1), lambda i: F.when(theirs(i).startswith("#"), -1).otherwise(1))
    level = F.aggregate(ahead, F.array(F.lit(0)), lambda a, x: F.concat(a, F.array(F.element_at(a, -1) + x)))
    parts = parts.withColumn("level", F.when(~F.col("enough"), level))
    n = F.col("part.to") - F.col("part.from")
    ends = lambda i: F.array_max(F.filter(F.sequence(i + F.col("least"), n), lambda j: F.get("level", j) >= F.get("level", i)))
    inner = F.array_max(F.transform(F.sequence(F.lit(0), n - F.col("least")), lambda i: F.struct((ends(i) - i).alias("size"), (-i).alias("at"))))
    parts = parts.withColumn("inner", F.when(~F.col("enough"), inner))
    parts = parts.withColumn("from", F.when(F.col("enough"), F.col("part.from")).otherwise(F.col("part.from") - F.col("inner.at")))
    parts = parts.withColumn("run_words", F.when(F.col("enough"), n).otherwise(F.col("inner.size"))).where("run_words is not null")
    same = F.slice("item", F.col("from") + 1, F.col("run_words")) == F.slice("words", F.col("from") + shift + 1, F.col("run_words"))
    return parts.select("doc_id", "item_id", "shift", "from", "run_words", same.alias("exact"))


def leaks(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, stride: int = STRIDE, min_run: int = MIN_RUN) -> DataFrame:
    """(doc_id, item_id, doc_word, item_word, run_words, exact): the longest such part for each document and item that leaks."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text")).withColumn("text_key", F.xxhash64("text"))
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), canonical(text).alias("item")).where("size(item) > 0")
    items = materialise(items.select("*", _types(F.col("item")).alias("item_types")), "items")
    # A run of `least` words holds a window that starts at a multiple of the step if least >= n + step - 1.
    least = F.least(F.size("item"), F.lit(min_run))
    n_words = F.least(least, F.lit(window))
    items = items.withColumn("n", n_words).withColumn("step", F.when(least >= n_words + stride - 1, stride).otherwise(1))
    sizes = sorted((r.n, r.step) for r in items.select("n", "step").distinct().collect())
    types = docs.select("doc_id", "text_key", _types(canonical(F.col("text"))).alias("types"))
    found = None
    for n, step in sizes:
        theirs = items.where((F.col("n") == n) & (F.col("step") == step))
        theirs = theirs.select("item_id", F.explode(_windows(F.col("item_types"), n, 1)).alias("w")).select("item_id", F.col("w.at").alias("item_at"), F.col("w.key").alias("key"))
        if theirs.count() <= BROADCAST_WINDOWS:
            theirs = F.broadcast(theirs)
        ours = types.select("doc_id", "text_key", F.explode(_windows(F.col("types"), n, step)).alias("w"))
        ours = ours.select("doc_id", "text_key", F.col("w.at").alias("at"), F.col("w.key").alias("key"))
        part = ours.join(theirs, "key").select("doc_id", "text_key", "item_id", (F.col("at") - F.col("item_at")).alias("shift"))
        found = part if found is None else found.unionByName(part)
    schema = "doc_id long, item_id long, doc_word int, item_word int, run_words int, exact boolean"
    if found is None:
        return small(docs.sparkSession, [], schema)
    found = materialise(found.distinct(), "alignments")
    near = by_ids(docs, materialise(found.select("doc_id", "text_key").distinct(), "leaking"), ["doc_id", "text_key"], "left_semi").dropDuplicates(["doc_id", "text_key"])
    near = near.select("doc_id", "text_key", canonical(F.col("text")).alias("words")).select("*", _types(F.col("words")).alias("types"))
    pairs = found.join(near, ["doc_id", "text_key"])
    pairs = pairs.join(F.broadcast(items) if items.count() <= BROADCAST_WINDOWS // 100 else items, "item_id")
    pairs = _pieces(pairs.withColumn("least", F.least(F.lit(min_run), F.size("item"))))
    best = F.max(F.struct("run_words", "exact", (-F.col("from")).alias("f"), "shift")).alias("best")
    out = pairs.groupBy("doc_id", "item_id").agg(best)
    return out.select("doc_id", "item_id", (F.col("best.shift") - F.col("best.f")).cast("int").alias("doc_word"), (-F.col("best.f")).cast("int").alias("item_word"), F.col("best.run_words").cast("int").alias("run_words"), F.col("best.exact").alias("exact"))
