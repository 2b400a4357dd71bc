"""Measures of effort and of progressive recall, as aggregates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def reduction(candidates: int, n: int, m: int) -> dict[str, float]:
    return {"candidates": candidates, "cartesian": n * m, "reduction": 1 - candidates / (n * m) if n * m else 0.0}


def _zero(x: Column) -> Column:
    return F.coalesce(x, F.lit(0.0))


def progressive(ranked: DataFrame, budgets: dict[float, int], all_related: int, run: Column | None = None) -> DataFrame:
    """One row per budget from (position, related): found, precision, recall, f, area, unit and ratio of progressive recall.

    recall is against the most that an ideal order finds within the budget; the area is that under the curve of
    related pairs found, and needs no running sum: a pair at position p counts in all later positions. Without related
    pairs, or with budget 0, all measures are 0. run: the place of the only budget in which a row counts (none: all).
    One aggregate gives all budgets, without a join or a row per budget and pair.
    """
    sums, rows = [], []
    for k, (f, b) in enumerate(budgets.items()):
        in_ = (F.col("position") <= F.lit(int(b))) & (F.lit(True) if run is None else run == k)
        sums += [F.count(F.when(in_, 1)).alias(f"found{k}"), F.coalesce(F.sum(F.when(in_, F.lit(int(b)).cast("long") - F.col("position") + 1)), F.lit(0)).alias(f"area{k}")]
        rows.append(F.struct(F.lit(float(f)).alias("fraction"), F.lit(int(b)).cast("long").alias("budget"), F.col(f"found{k}").alias("found"), F.col(f"area{k}").alias("area")))
    d = ranked.where("related").agg(*sums).select(F.inline(F.array(*rows)))
    best = F.least("budget", F.lit(int(all_related)))
    d = d.withColumn("best", best).withColumn("ideal_area", F.expr("best * (best + 1) / 2 + (budget - best) * best"))
    ratio = lambda a, b: F.when(b > 0, a / b).otherwise(0.0)
    d = d.withColumn("precision", ratio(F.col("found"), F.col("budget"))).withColumn("recall", ratio(F.col("found"), F.col("best")))
    f = F.when(F.col("precision") + F.col("recall") > 0, 2 * F.col("precision") * F.col("recall") / (F.col("precision") + F.col("recall"))).otherwise(0.0)
    d = d.withColumn("f_measure", f).withColumn("unit", ratio(F.col("area"), F.col("budget") * F.col("best"))).withColumn("ratio", ratio(F.col("area"), F.col("ideal_area")))
    return d.select("fraction", "budget", "found", "precision", "recall", "f_measure", "area", "unit", "ratio", (1 - F.col("recall")).alias("recall_gap"), (1 - F.col("ratio")).alias("ratio_gap"))


def recall_curve(ranked: DataFrame, every: int) -> DataFrame:
    """(position, found) at each `every`-th position: sums per step, then a running sum over the steps."""
    step = F.ceil(F.col("position") / every).cast("long")
    sums = ranked.groupBy(step.alias("step")).agg(F.sum(F.col("related").cast("long")).alias("n"), F.max("position").alias("position"))
    return sums.select("position", F.sum("n").over(Window.orderBy("step").rowsBetween(Window.unboundedPreceding, 0)).alias("found"))


def load_skew(dealt: DataFrame, key: list[str]) -> DataFrame:
    n = dealt.groupBy(*key).agg(F.count(F.lit(1)).alias("n"))
    return n.agg(F.count(F.lit(1)).alias("parts"), F.min("n").alias("least"), F.max("n").alias("most"), F.avg("n").alias("mean"))


def qualifying_ratio(related: int, candidates: int) -> float:
    return related / candidates if candidates else 0.0


def mean_gaps(evaluated: DataFrame) -> DataFrame:
    """(method, recall_gap, ratio_gap): mean distances from the ideal over budgets, of rows (method, recall, ratio)."""
    return evaluated.where("method <> 'ideal'").groupBy("method").agg(F.avg(1 - F.col("recall")).alias("recall_gap"), F.avg(1 - F.col("ratio")).alias("ratio_gap"))


#: Bytes of a geometry's box and id, and of a point.
HEAD_BYTES, POINT_BYTES = 48, 16


def resident_bytes(source: DataFrame, target: DataFrame) -> DataFrame:
    """(frugal, intensive): bytes of the smaller side, and of both."""
    size = lambda d, c: d.agg((F.count(F.lit(1)) * HEAD_BYTES + F.coalesce(F.sum("npoints"), F.lit(0)) * POINT_BYTES).alias(c))
    both = size(source, "a").crossJoin(size(target, "b"))  # one row each
    return both.select(F.least("a", "b").alias("frugal"), (F.col("a") + F.col("b")).alias("intensive"))


def index_bytes(source: DataFrame, capacity: int = 16) -> DataFrame:
    """(tree, bytes, box_bytes) of each tree over the sources of every cell, summed; built in the tasks."""
    import numpy as np
    import pyarrow as pa

    from spatial_links.operators import local_index as I
    from spatial_links.operators import partitioned as P

    sample = P.sampled(source, source.limit(0))
    cells = P.make_cells("kdb", sample)

    def run(table: pa.Table) -> pa.Table:
        b = np.column_stack([table.column(c).to_numpy() for c in P.BOX]).reshape(-1, 4)
        trees = {"str": I.str_tree(b, capacity), "crtree": I.cr_tree(b, capacity), "rtree": I.r_tree(b, capacity), "quadtree": I.QuadTree(b, capacity)}
        boxes = [sum(x[0].nbytes for x in t.levels) if hasattr(t, "levels") else None for t in trees.values()]
        return pa.table({"tree": list(trees), "bytes": pa.array([t.nbytes() for t in trees.values()], pa.int64()), "box_bytes": pa.array(boxes, pa.int64())})

    each = P.dealt(source.select("gid", *P.BOX), cells).groupBy("pid").applyInArrow(run, "tree string, bytes long, box_bytes long")
    return each.groupBy("tree").agg(F.sum("bytes").alias("bytes"), F.sum("box_bytes").alias("box_bytes"))


def growth(first: float, last: float) -> float:
    return last / first if first else 0.0
