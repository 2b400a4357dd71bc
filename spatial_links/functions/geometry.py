"""Columns of a geometry and scalar expressions on them, all inside whole-stage code generation."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SCHEMA = (
    "gid bigint, uri string, geom_type string, dim tinyint, npoints int, xs array<double>, ys array<double>, ring_ends array<int>, "
    "xmin double, ymin double, xmax double, ymax double, attrs map<string,string>"
)
BOX = ("xmin", "ymin", "xmax", "ymax")
SHAPE = ("geom_type", "xs", "ys", "ring_ends")


def with_mbr(df: DataFrame) -> DataFrame:
    """Adds npoints and the bounding box, from the coordinate arrays."""
    return df.select("*", F.size("xs").alias("npoints"), F.array_min("xs").alias("xmin"), F.array_min("ys").alias("ymin"), F.array_max("xs").alias("xmax"), F.array_max("ys").alias("ymax"))


def boxes_meet(a: str = "s_", b: str = "t_") -> Column:
    """Closed boxes share a point."""
    c = lambda p, k: F.col(p + k)
    return (c(a, "xmin") <= c(b, "xmax")) & (c(b, "xmin") <= c(a, "xmax")) & (c(a, "ymin") <= c(b, "ymax")) & (c(b, "ymin") <= c(a, "ymax"))


def in_window(xmin: float, ymin: float, xmax: float, ymax: float) -> Column:
    """Boxes that meet a window: flat comparisons that reach the Parquet row groups."""
    return (F.col("xmin") <= xmax) & (F.col("xmax") >= xmin) & (F.col("ymin") <= ymax) & (F.col("ymax") >= ymin)


def box_contains(a: str = "s_", b: str = "t_") -> Column:
    c = lambda p, k: F.col(p + k)
    return (c(a, "xmin") <= c(b, "xmin")) & (c(a, "ymin") <= c(b, "ymin")) & (c(a, "xmax") >= c(b, "xmax")) & (c(a, "ymax") >= c(b, "ymax"))


def _legs() -> Column:
    """The segments of a geometry, none between two rings."""
    at = F.sequence(F.lit(0), F.size("xs") - 2)
    own = F.filter(at, lambda i: ~F.array_contains("ring_ends", i + 1))
    return F.transform(own, lambda i: F.struct(F.get("xs", i).alias("x1"), F.get("ys", i).alias("y1"), F.get("xs", i + 1).alias("x2"), F.get("ys", i + 1).alias("y2")))


def segments() -> Column:
    return _legs()


def length() -> Column:
    d = lambda s: F.sqrt(F.pow(s["x2"] - s["x1"], F.lit(2)) + F.pow(s["y2"] - s["y1"], F.lit(2)))
    return F.aggregate(F.transform(_legs(), d), F.lit(0.0), lambda a, b: a + b)


def _ring_area(first: Column, last: Column) -> Column:
    at = F.when(last - first >= 2, F.sequence(first, last - 2)).otherwise(F.array().cast("array<int>"))
    part = F.transform(at, lambda i: F.get("xs", i) * F.get("ys", i + 1) - F.get("xs", i + 1) * F.get("ys", i))
    return F.abs(F.aggregate(part, F.lit(0.0), lambda a, b: a + b)) / 2


def area() -> Column:
    """Shell area less hole areas; 0 for lines."""
    starts = F.concat(F.array(F.lit(0)), F.slice("ring_ends", 1, F.size("ring_ends") - 1))
    rings = F.transform(F.arrays_zip(starts.alias("a"), F.col("ring_ends").alias("b")), lambda r: _ring_area(r["a"], r["b"]))
    whole = 2 * F.get(rings, F.lit(0)) - F.aggregate(rings, F.lit(0.0), lambda a, b: a + b)
    return F.when(F.col("geom_type") == "P", whole).otherwise(F.lit(0.0))


def vertex_mean(axis: str) -> Column:
    """Mean of a coordinate over the vertices (a ring's closing vertex counts)."""
    return F.aggregate(axis, F.lit(0.0), lambda a, b: a + b) / F.size(axis)


def to_wkt() -> Column:
    number = lambda v: F.when(v == F.floor(v), F.format_string("%d", v.cast("long"))).otherwise(v.cast("string"))
    point = F.transform(F.arrays_zip("xs", "ys"), lambda p: F.concat_ws(" ", number(p["xs"]), number(p["ys"])))
    starts = F.concat(F.array(F.lit(0)), F.slice("ring_ends", 1, F.size("ring_ends") - 1))
    rings = F.transform(F.arrays_zip(starts.alias("a"), F.col("ring_ends").alias("b")), lambda r: F.concat(F.lit("("), F.array_join(F.slice(point, r["a"] + 1, r["b"] - r["a"]), ", "), F.lit(")")))
    return F.when(F.col("geom_type") == "L", F.concat(F.lit("LINESTRING "), F.get(rings, F.lit(0)))).otherwise(F.concat(F.lit("POLYGON ("), F.array_join(rings, ", "), F.lit(")")))


def prefixed(df: DataFrame, prefix: str, columns: tuple[str, ...]) -> DataFrame:
    """`gid` as sid or tid, and the named columns behind s_ or t_."""
    return df.select(F.col("gid").alias(f"{prefix}id"), *(F.col(c).alias(f"{prefix}_{c}") for c in columns))
