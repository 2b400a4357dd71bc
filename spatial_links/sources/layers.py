"""Layers: deterministic geometry sets on an integer lattice, computed from the given tables.

Every layer has the canonical geometry columns (SCHEMA of `spatial_links.functions.geometry`) and, for lattice layers,
x, y, w, h and shape, from which a SQL oracle can rebuild it.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from spatial_links.functions.geometry import with_mbr
from spatial_links.plans.shared import new_path, shared_dir

#: name -> (return flag, line numbers kept, width, height, shape, scale, shift), as SQL over qty, pk, sk, ln.
RECIPES = {
    "lakes": ("R", "ln <= 3", "1 + qty % 3", "1 + pk % 3", "area"),
    "parks": ("N", "true", "1 + qty % 4", "1 + pk % 4", "area"),
    "crags": ("A", "ln > 4", "1 + qty % 4", "1 + pk % 4", "area"),
    "lots": ("N", "true", "1 + qty % 2", "1 + pk % 2", "rect"),
    "stars": ("R", "ln <= 3", "2 * (2 + qty % 3) + 1", "2 * (2 + pk % 3) + 1", "plus"),
    "bursts": ("N", "ln <= 4", "2 * (2 + qty % 3) + 1", "2 * (2 + pk % 3) + 1", "plus"),
    "streams": ("A", "true", "1 + qty % 3", "1 + pk % 3", "path3"),
    "roads": ("A", "ln <= 4", "2 + qty % 5", "2 + pk % 5", "hook"),
    "detours": ("A", "true", "4 + qty % 5", "4 + pk % 5", "hook"),
    "hooks": ("A", "true", "4 + qty % 4", "4 + pk % 4", "hook"),
    "tracks": ("R", "ln <= 3", "1 + qty % 2", "1 + pk % 2", "path2"),
    "edges": ("N", "true", "1 + qty % 2", "1 + pk % 2", "path2"),
    "ponds4": ("R", "ln <= 3", "1 + qty % 2", "1 + pk % 2", "rect"),
    "hooks4": ("A", "ln <= 2", "4 * (12 + qty % 8)", "4 * (12 + pk % 8)", "hook"),
}
#: The shape column by kind of recipe.
SHAPES = {
    "area": "case when sk % 4 = 2 and w >= 2 and h >= 2 then 'L' when sk % 4 = 3 and w >= 3 and h >= 3 then 'ring' else 'rect' end",
    "rect": "'rect'",
    "plus": "'plus'",
    "hook": "'hook'",
    "path3": "case sk % 3 when 0 then 'hline' when 1 then 'vline' else 'hook' end",
    "path2": "case sk % 2 when 0 then 'hline' else 'vline' end",
}
PAIRS = {
    "p1": ("lakes", "streams"), "p2": ("ponds4", "hooks4"), "p3": ("lakes", "parks"), "p4": ("parks", "mixed"), "p5": ("tracks", "edges"),
    "p6": ("hooks", "lots"), "p7": ("stars", "bursts"), "p8": ("stars", "detours"), "p9": ("stars", "lots"),
}
LATTICE = ("gid", "x", "y", "w", "h", "shape")


def place_sql(name: str, axis: str) -> str:
    if name == "ponds4":
        return f"4 * {axis}"
    if name == "hooks4":
        return f"4 * {axis} + case when sk % 16 = 0 then 0 else 3 end"
    return axis


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def base_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """gid, flag, x, y, qty, pk, sk, ln, orderkey: the lineitem rows that are alone in their (key, flag)."""
    li = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_returnflag", "l_shipdate")
    row = F.struct(
        F.expr("cast(l_partkey div 4 as int)").alias("x"),
        F.expr("cast(datediff(l_shipdate, date '1995-01-01') div 14 as int)").alias("y"),
        F.col("l_quantity").cast("int").alias("qty"), F.col("l_partkey").alias("pk"), F.col("l_suppkey").alias("sk"),
    )
    one = li.groupBy("l_orderkey", "l_linenumber", F.col("l_returnflag").alias("flag")).agg(F.count(F.lit(1)).alias("n"), F.min(row).alias("r")).where("n = 1")
    return one.select((F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("gid"), "flag", "r.*", F.col("l_linenumber").alias("ln"), F.col("l_orderkey").alias("orderkey"))


def _lattice(rows: DataFrame, name: str) -> DataFrame:
    flag, keep, w, h, shape = RECIPES[name]
    rows = rows.where((F.col("flag") == flag) & F.expr(keep)).select("gid", "x", "y", "qty", "pk", "sk", "orderkey", F.expr(f"cast({w} as int)").alias("w"), F.expr(f"cast({h} as int)").alias("h"))
    rows = rows.withColumn("shape", F.expr(SHAPES[shape]))
    size = lambda c, none: F.when(F.col("shape") == none, 0).otherwise(F.col(c))
    return rows.select("gid", F.expr(place_sql(name, "x")).cast("int").alias("x"), F.expr(place_sql(name, "y")).cast("int").alias("y"), size("w", "vline").alias("w"), size("h", "hline").alias("h"), "shape", "orderkey")


def _points(shape: Column) -> tuple[Column, Column, Column]:
    """(xs, ys, ring_ends) of a lattice shape."""
    x, y, w, h = (F.col(c).cast("double") for c in ("x", "y", "w", "h"))
    mx, my = x + F.floor(w / 2), y + F.floor(h / 2)
    a = F.array
    r, t = x + w, y + h
    forms = {
        "rect": (a(x, r, r, x, x), a(y, y, t, t, y), a(F.lit(5))),
        "L": (a(x, r, r, r - 1, r - 1, x, x), a(y, y, t - 1, t - 1, t, t, y), a(F.lit(7))),
        "ring": (a(x, r, r, x, x, x + 1, x + 1, r - 1, r - 1, x + 1), a(y, y, t, t, y, y + 1, t - 1, t - 1, y + 1, y + 1), a(F.lit(5), F.lit(10))),
        "plus": (a(mx, mx + 1, mx + 1, r, r, mx + 1, mx + 1, mx, mx, x, x, mx, mx), a(y, y, my, my, my + 1, my + 1, t, t, my + 1, my + 1, my, my, y), a(F.lit(13))),
        "hline": (a(x, r), a(y, y), a(F.lit(2))),
        "vline": (a(x, x), a(y, t), a(F.lit(2))),
        "hook": (a(x, r, r), a(y, y, t), a(F.lit(3))),
    }
    out = []
    for i in range(3):
        e = F.when(shape == "rect", forms["rect"][i])
        for k in list(forms)[1:]:
            e = e.when(shape == k, forms[k][i])
        out.append(e)
    return out[0], out[1], out[2]


def lattice_layer(rows: DataFrame, name: str) -> DataFrame:
    d = _lattice(rows, name)
    xs, ys, ends = _points(F.col("shape"))
    line = F.col("shape").isin("hline", "vline", "hook")
    d = d.select(
        "gid", F.concat(F.lit(f"urn:{name}:"), F.col("gid").cast("string")).alias("uri"), F.when(line, "L").otherwise("P").alias("geom_type"), F.when(line, 1).otherwise(2).cast("tinyint").alias("dim"),
        xs.alias("xs"), ys.alias("ys"), ends.alias("ring_ends"), F.create_map(F.lit("layer"), F.lit(name), F.lit("orderkey"), F.col("orderkey").cast("string")).alias("attrs"), "x", "y", "w", "h", "shape",
    )
    # The box of a lattice shape is known without its points.
    d = d.select("*", F.size("xs").alias("npoints"), *(F.expr(e).cast("double").alias(c) for c, e in (("xmin", "x"), ("ymin", "y"), ("xmax", "x + w"), ("ymax", "y + h"))))
    return d


_stored: dict[tuple, tuple[str, object]] = {}


def stored(spark: SparkSession, sf_dir: str, name: str, make) -> DataFrame:
    """A table written once a session to the shared folder, and read from there by all that use it."""
    key = (spark.sparkContext.applicationId, shared_dir(spark), sf_dir, name)
    if key in _stored:
        path, schema = _stored[key]
        where = spark._jvm.org.apache.hadoop.fs.Path(path)
        if where.getFileSystem(spark._jsc.hadoopConfiguration()).exists(where):
            return spark.read.schema(schema).parquet(path)
    path, d = new_path(spark, f"layer-{name}"), make()
    d.write.parquet(path)
    _stored[key] = (path, d.schema)
    return spark.read.schema(d.schema).parquet(path)


def made(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A layer as a plan over the given tables."""
    if name in RECIPES:
        return lattice_layer(stored(spark, sf_dir, "base", lambda: base_rows(spark, sf_dir)), name)
    return {"mixed": mixed, "routes": routes, "walks": walks, "zones": zones, "visits": visits, "triangles": triangles}[name](spark, sf_dir)


def layer(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A layer by name as a written table: one of RECIPES, mixed, routes, walks, zones, visits or triangles."""
    return stored(spark, sf_dir, name, lambda: made(spark, sf_dir, name))


def mixed(spark: SparkSession, sf_dir: str) -> DataFrame:
    return made(spark, sf_dir, "roads").unionByName(made(spark, sf_dir, "crags"))


def pair(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, DataFrame]:
    s, t = PAIRS[name]
    return layer(spark, sf_dir, s), layer(spark, sf_dir, t)


def _stops(spark: SparkSession, sf_dir: str) -> DataFrame:
    """gid and p, the distinct places of an order's lines by ship date (at most seven), of all orders with two or more."""
    rows = table(spark, sf_dir, "lineitem")
    rows = rows.select("l_orderkey", F.expr("cast(l_partkey div 4 as int)").alias("x"), F.expr("cast(datediff(l_shipdate, date '1995-01-01') div 14 as int)").alias("y"), "l_shipdate", "l_linenumber")
    rows = rows.groupBy("l_orderkey", "x", "y").agg(F.min(F.struct("l_shipdate", "l_linenumber")).alias("first"))
    return rows.groupBy(F.col("l_orderkey").alias("gid")).agg(F.sort_array(F.collect_list(F.struct("first", "x", "y"))).alias("p")).where("size(p) >= 2")


def _lines(rows: DataFrame, name: str, x, y) -> DataFrame:
    xs, ys = F.transform("p", lambda q: x(q).cast("double")), F.transform("p", lambda q: y(q).cast("double"))
    return with_mbr(rows.select("gid", F.concat(F.lit(f"urn:{name}:"), F.col("gid").cast("string")).alias("uri"), F.lit("L").alias("geom_type"), F.lit(1).cast("tinyint").alias("dim"), xs.alias("xs"), ys.alias("ys"), F.array(F.size("p")).alias("ring_ends"), F.create_map(F.lit("layer"), F.lit(name)).alias("attrs")))


def routes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A LineString through the places of each order, by ship date."""
    return _lines(_stops(spark, sf_dir), "routes", lambda q: q["x"], lambda q: q["y"])


def walks(spark: SparkSession, sf_dir: str, reach: int = 24) -> DataFrame:
    """The same stops within `reach` of the first one: slanting lines of bounded length, crowded where orders start."""
    first = lambda k: F.get("p", F.lit(0))[k]
    rows = _stops(spark, sf_dir)
    rows = rows.withColumn("p", F.transform("p", lambda q, i: F.struct((first("x") + F.pmod(q["x"] - first("x"), F.lit(reach))).alias("x"), (first("y") + F.pmod(q["y"] - first("y"), F.lit(reach))).alias("y"))))
    rows = rows.withColumn("p", F.array_distinct("p")).where("size(p) >= 2")
    return _lines(rows, "walks", lambda q: q["x"], lambda q: q["y"])


def zones(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("gid"), F.expr("cast((s_suppkey * 37) % 480 as int)").alias("x"), F.expr("cast((s_suppkey * 53) % 700 as int)").alias("y"), F.lit(20).alias("w"), F.lit(24).alias("h"), F.lit("rect").alias("shape"))
    xs, ys, ends = _points(F.col("shape"))
    d = d.select("gid", F.concat(F.lit("urn:zones:"), F.col("gid").cast("string")).alias("uri"), F.lit("P").alias("geom_type"), F.lit(2).cast("tinyint").alias("dim"), xs.alias("xs"), ys.alias("ys"), ends.alias("ring_ends"), F.create_map(F.lit("layer"), F.lit("zones")).alias("attrs"), *LATTICE[1:])
    return with_mbr(d)


def as_visits(events: DataFrame) -> DataFrame:
    """Events (a table or a stream) as horizontal lines at their hour."""
    hours = F.expr("cast((unix_timestamp(cast(ts as timestamp)) - unix_timestamp(timestamp '2024-01-01 00:00:00')) div 3600 as int)")
    d = events.select(F.col("event_id").alias("gid"), F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "props", F.col("value").cast("int").alias("x"), hours.alias("y"), F.expr("cast(1 + event_id % 10 as int)").alias("w"), F.lit(0).alias("h"), F.lit("hline").alias("shape"))
    x, y, w = (F.col(c).cast("double") for c in ("x", "y", "w"))
    d = d.select(F.col("gid"), F.concat(F.lit("urn:visits:"), F.col("gid").cast("string")).alias("uri"), F.lit("L").alias("geom_type"), F.lit(1).cast("tinyint").alias("dim"), F.array(x, x + w).alias("xs"), F.array(y, y).alias("ys"), F.array(F.lit(2)).alias("ring_ends"), F.create_map(F.lit("layer"), F.lit("visits")).alias("attrs"), *LATTICE[1:], "ts", "user_id", "event_type", "props")
    return with_mbr(d)


def visits(spark: SparkSession, sf_dir: str) -> DataFrame:
    return as_visits(table(spark, sf_dir, "events"))


def triangles(spark: SparkSession, sf_dir: str, scale: float = 1000.0, rounded: bool = True) -> DataFrame:
    d = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("gid"), F.slice("embedding", 1, 6).alias("e"))
    value = (lambda i: F.round(F.get("e", F.lit(i)).cast("double") * scale)) if rounded else (lambda i: F.get("e", F.lit(i)).cast("double"))
    d = d.select("gid", F.concat(F.lit("urn:triangles:"), F.col("gid").cast("string")).alias("uri"), F.lit("P").alias("geom_type"), F.lit(2).cast("tinyint").alias("dim"), F.array(*(value(i) for i in (0, 2, 4, 0))).alias("xs"), F.array(*(value(i) for i in (1, 3, 5, 1))).alias("ys"), F.array(F.lit(4)).alias("ring_ends"), F.create_map(F.lit("layer"), F.lit("triangles")).alias("attrs"))
    return with_mbr(d)
