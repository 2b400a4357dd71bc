"""SQL names for the predicates, tiles and weights, and a spatial join that is planned as a tile join."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from spatial_links.operators import grid, verify
from spatial_links.plans.methods import MethodSpec, pair_matrices


@F.udtf(returnType=T.StructType([T.StructField("tx", T.LongType()), T.StructField("ty", T.LongType())]))
class TilesOf:
    """The tiles that a box meets, for lateral calls from SQL (which Spark does not allow to Arrow table functions)."""

    def eval(self, xmin: float, ymin: float, xmax: float, ymax: float, w: float, h: float):
        import math

        for x in range(math.floor(xmin / w), math.floor(xmax / w) + 1):
            for y in range(math.floor(ymin / h), math.floor(ymax / h) + 1):
                yield x, y


_BOX2 = "ax1 double, ay1 double, ax2 double, ay2 double, bx1 double, by1 double, bx2 double, by2 double"
_TILES = f"{_BOX2}, w double, h double"
_SHARED = "(greatest(0, floor(least(ax2, bx2) / w) - floor(greatest(ax1, bx1) / w) + 1) * greatest(0, floor(least(ay2, by2) / h) - floor(greatest(ay1, by1) / h) + 1))"
_OF = lambda p: f"((floor({p}x2 / w) - floor({p}x1 / w) + 1) * (floor({p}y2 / h) - floor({p}y1 / h) + 1))"
_IN = "(greatest(0D, least(ax2, bx2) - greatest(ax1, bx1)) * greatest(0D, least(ay2, by2) - greatest(ay1, by1)))"
_UNION = f"((ax2 - ax1) * (ay2 - ay1) + (bx2 - bx1) * (by2 - by1) - {_IN})"


def register_functions(spark: SparkSession) -> list[str]:
    """Registers sl_* functions in the session; scalar ones are SQL functions, so they are inlined and codegen'd."""
    spark.udf.register("sl_relate", verify.relate_matrix)
    spark.udtf.register("sl_tiles", TilesOf)
    sql = {
        "sl_boxes_meet": (_BOX2, "boolean", "ax1 <= bx2 and bx1 <= ax2 and ay1 <= by2 and by1 <= ay2"),
        "sl_cf": (_TILES, "double", f"cast({_SHARED} as double)"),
        "sl_js": (_TILES, "double", f"cast({_SHARED} as double) / ({_OF('a')} + {_OF('b')} - {_SHARED})"),
        "sl_chi2": (f"{_TILES}, n double", "double", f"case when {_OF('a')} * {_OF('b')} * (n - {_OF('a')}) * (n - {_OF('b')}) > 0 then n * power({_SHARED} * (n - {_OF('a')} - {_OF('b')} + {_SHARED}) - ({_OF('a')} - {_SHARED}) * ({_OF('b')} - {_SHARED}), 2) / ({_OF('a')} * {_OF('b')} * (n - {_OF('a')}) * (n - {_OF('b')})) else 0D end"),
        "sl_mbro": (_BOX2, "double", f"case when {_UNION} > 0 then {_IN} / {_UNION} else 0D end"),
        "sl_isp": ("a int, b int", "double", "1D / (a + b)"),
    }
    for name, (args, kind, body) in sql.items():
        spark.sql(f"create or replace temporary function {name}({args}) returns {kind} return {body}")
    dims = "m string, da tinyint, db tinyint"
    like = lambda mask: f"m rlike '^{mask.replace('*', '.').replace('T', '[012]')}$'"
    bodies = {r: " or ".join(map(like, masks)) for r, masks in verify.MASKS.items()}
    bodies["intersects"] = f"not ({like('FF*FF****')})"
    bodies["crosses"] = f"case when da < db then {like('T*T******')} when da > db then {like('T*****T**')} when da = 1 then {like('0********')} else false end"
    bodies["overlaps"] = f"da = db and case when da = 1 then {like('1*T***T**')} else {like('T*T***T**')} end"
    for r, body in bodies.items():
        spark.sql(f"create or replace temporary function sl_{r}({dims}) returns boolean return {body}")
    return ["sl_relate", "sl_tiles", *sql, *(f"sl_{r}" for r in bodies)]


def spatial_join_sql(spark: SparkSession, left: str, right: str, predicate: str, spec: MethodSpec | str = "distributed_grid") -> DataFrame:
    """Two views of geometries joined on a relation: planned as a tile join, not as a nested loop around a Python predicate."""
    s, t = spark.table(left), spark.table(right)
    m = pair_matrices(s, t, spec)
    return m.where(verify.relation(predicate, F.col("matrix"), F.col("s_dim"), F.col("t_dim"))).select("sid", "tid")


def tiles_in_sql(layer: DataFrame, tile: grid.Tile) -> DataFrame:
    """(gid, tx, ty) by the table function."""
    spark = layer.sparkSession
    layer.select("gid", "xmin", "ymin", "xmax", "ymax").createOrReplaceTempView("sl_layer")
    register_functions(spark)
    return spark.sql(f"select gid, tx, ty from sl_layer, lateral sl_tiles(xmin, ymin, xmax, ymax, {tile.w!r}D, {tile.h!r}D)")
