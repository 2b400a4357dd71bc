"""Verification: one intersection matrix per candidate pair, and the nine positive relations read from it."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from spatial_links.functions.geometry import SHAPE, prefixed
from spatial_links.functions.kernel import relate

#: The relations' masks, in the OGC notation; a relation holds if any of its masks matches.
MASKS = {
    "equals": ("T*F**FFF*",),
    "touches": ("FT*******", "F**T*****", "F***T****"),
    "within": ("T*F**F***",),
    "contains": ("T*****FF*",),
    "covers": ("T*****FF*", "*T****FF*", "***T**FF*", "****T*FF*"),
    "covered_by": ("T*F**F***", "*TF**F***", "**FT*F***", "**F*TF***"),
}
RELATIONS = ("contains", "covered_by", "covers", "crosses", "equals", "intersects", "overlaps", "touches", "within")


@F.arrow_udf(T.StringType())
def relate_matrix(a_type: pa.Array, a_xs: pa.Array, a_ys: pa.Array, a_ends: pa.Array, b_type: pa.Array, b_xs: pa.Array, b_ys: pa.Array, b_ends: pa.Array) -> pa.Array:
    """Nine characters of F, 0, 1, 2 for each pair."""
    flags = [np.asarray(pc.equal(t, "P").fill_null(False)) for t in (a_type, b_type)]
    return pa.array(relate(flags[0], a_xs, a_ys, a_ends, flags[1], b_xs, b_ys, b_ends), pa.string())


def matrix_batch(b: pa.RecordBatch) -> pa.RecordBatch:
    """(position, sid, tid, s_dim, t_dim, matrix) of a batch that carries both geometries."""
    side = lambda p: [b.column(p + c) for c in SHAPE]
    (a, *one), (c, *two) = side("s_"), side("t_")
    flags = [np.asarray(pc.equal(t, "P").fill_null(False)) for t in (a, c)]
    cols = [b.column(k) for k in ("position", "sid", "tid", "s_dim", "t_dim")]
    return pa.RecordBatch.from_arrays([*cols, pa.array(relate(flags[0], *one, flags[1], *two), pa.string())], names=["position", "sid", "tid", "s_dim", "t_dim", "matrix"])


def matrix_of(a: str = "s_", b: str = "t_") -> Column:
    return relate_matrix(*(F.col(p + c) for p in (a, b) for c in SHAPE))


def _matches(matrix: Column, mask: str) -> Column:
    return matrix.rlike("^" + mask.replace("*", ".").replace("T", "[012]") + "$")


def relation(name: str, matrix: Column, a_dim: Column, b_dim: Column) -> Column:
    """Whether a relation holds, as a codegen'd expression on the matrix."""
    if name == "intersects":
        return ~_matches(matrix, "FF*FF****")
    if name == "crosses":
        return F.when(a_dim < b_dim, _matches(matrix, "T*T******")).when(a_dim > b_dim, _matches(matrix, "T*****T**")).when(a_dim == 1, _matches(matrix, "0********")).otherwise(F.lit(False))
    if name == "overlaps":
        return (a_dim == b_dim) & F.when(a_dim == 1, _matches(matrix, "1*T***T**")).otherwise(_matches(matrix, "T*T***T**"))
    if name == "disjoint":
        return _matches(matrix, "FF*FF****")
    out = F.lit(False)
    for mask in MASKS[name]:
        out = out | _matches(matrix, mask)
    return out


def fills_box(p: str = "") -> Column:
    """Whether a geometry is all of its box: a rectangle along the axes, or one segment along an axis."""
    x, y = (lambda i: F.get(f"{p}xs", F.lit(i))), (lambda i: F.get(f"{p}ys", F.lit(i)))
    n, rings = F.size(f"{p}xs"), F.size(f"{p}ring_ends")
    flat = (F.col(f"{p}geom_type") == "L") & (n == 2) & ((x(0) == x(1)) | (y(0) == y(1)))
    closed = (x(0) == x(4)) & (y(0) == y(4)) & (x(0) != x(2)) & (y(0) != y(2))
    turn = lambda a, b: (a(1) == a(2)) & (a(3) == a(0)) & (b(1) == b(0)) & (b(3) == b(2))
    rect = (F.col(f"{p}geom_type") == "P") & (n == 5) & (rings == 1) & closed & (turn(x, y) | turn(y, x))
    return F.coalesce(flat | rect, F.lit(False))


def transpose(matrix: Column) -> Column:
    """The matrix of the pair the other way round."""
    return F.concat(*(F.substring(matrix, k, 1) for k in (1, 4, 7, 2, 5, 8, 3, 6, 9)))


def attach(pairs: DataFrame, source: DataFrame, target: DataFrame) -> DataFrame:
    """Joins the geometry columns to (sid, tid) pairs: late materialisation for filters that carry ids only."""
    s = prefixed(source, "s", ("dim", *SHAPE))
    t = prefixed(target, "t", ("dim", *SHAPE))
    return pairs.join(s, "sid").join(t, "tid")


def matrices(carried: DataFrame) -> DataFrame:
    """(…, s_dim, t_dim, matrix) from pairs that carry both geometries, which are dropped."""
    drop = [p + c for p in ("s_", "t_") for c in SHAPE]
    return carried.withColumn("matrix", matrix_of()).drop(*drop)


def with_relations(df: DataFrame, relations: tuple[str, ...] = RELATIONS) -> DataFrame:
    """Adds a boolean column for each relation; only the asked masks are evaluated."""
    m, a, b = F.col("matrix"), F.col("s_dim"), F.col("t_dim")
    return df.select("*", *(relation(r, m, a, b).alias(r) for r in relations))


def links(df: DataFrame, relations: tuple[str, ...] = RELATIONS) -> DataFrame:
    """(sid, relation, tid) triples from the matrices of pairs."""
    m, a, b = F.col("matrix"), F.col("s_dim"), F.col("t_dim")
    held = F.array_compact(F.array(*(F.when(relation(r, m, a, b), F.lit(r)) for r in relations)))
    return df.select("sid", F.explode(held).alias("relation"), "tid")


def relation_counts(df: DataFrame) -> DataFrame:
    """One row per relation with its pairs, from matrices; all relations in one pass (partial and final sums)."""
    flags = with_relations(df).agg(*(F.sum(F.col(r).cast("long")).alias(r) for r in RELATIONS))
    pairs = F.array(*(F.struct(F.lit(r).alias("relation"), F.coalesce(F.col(r), F.lit(0)).alias("pairs")) for r in RELATIONS))
    return flags.select(F.inline(pairs))


def one_relation_runs(source: DataFrame, target: DataFrame, candidates, relations: tuple[str, ...] = RELATIONS) -> DataFrame:
    """The baseline that repeats the whole work for each relation: one filter and one verification per run."""
    out = None
    for r in relations:
        run = links(matrices(candidates(source, target)), (r,))
        out = run if out is None else out.unionByName(run)
    return out


def is_disjoint(matrix: Column) -> Column:
    return _matches(matrix, "FF*FF****")


def disjoint_pairs(source: DataFrame, target: DataFrame, related: DataFrame, limit: int = 50_000_000) -> DataFrame:
    """Closed world: all pairs of two small inputs that have no related pair. Refuses products over `limit`."""
    n, m = source.count(), target.count()
    if n * m > limit:
        raise ValueError(f"{n} x {m} pairs are over the limit of {limit}")
    every = source.select(F.col("gid").alias("sid")).crossJoin(target.select(F.col("gid").alias("tid")))
    return every.join(related.select("sid", "tid"), ["sid", "tid"], "left_anti")


def disjoint_counts(source: DataFrame, target: DataFrame, related: DataFrame) -> DataFrame:
    """(sid, disjoint): closed world as numbers, all targets less the related ones of each source; no pair is made."""
    n = related.groupBy("sid").agg(F.count(F.lit(1)).alias("n"))
    every = target.agg(F.count(F.lit(1)).alias("m"))
    d = source.select(F.col("gid").alias("sid")).join(n, "sid", "left").crossJoin(F.broadcast(every))  # one row
    return d.select("sid", (F.col("m") - F.coalesce("n", F.lit(0))).alias("disjoint"))
