"""Readers of geometry files. Each returns the canonical columns of good rows, and rejected rows with a reason.

All parsing is by built-in functions. `parsed` holds what a format yields (uri, wkt, attrs, line); `clean` decides.
"""

from __future__ import annotations

import json
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from spatial_links.functions.geometry import with_mbr

_NUMBER = r"[-+]?(?:[0-9]+\.?[0-9]*|\.[0-9]+)(?:[eE][-+]?[0-9]+)?"
_NONE = "cast(null as map<string,string>)"


def _parsed(df: DataFrame, uri: Column, wkt: Column, line: Column, attrs: Column | None = None) -> DataFrame:
    return df.select(uri.cast("string").alias("uri"), wkt.alias("wkt"), line.alias("line"), (F.expr(_NONE) if attrs is None else attrs).alias("attrs"))


def read_wkt(spark: SparkSession, path: str) -> DataFrame:
    """One geometry a line."""
    d = spark.read.text(path)
    return _parsed(d, F.lit(None), F.col("value"), F.col("value"))


def read_csv(spark: SparkSession, path: str, sep: str = ",", header: bool = True, geometry: int = 0, uri: int | None = None) -> DataFrame:
    """Separated text; the geometry's column by index. Columns are read as text: no inference."""
    d = spark.read.option("header", header).option("sep", sep).option("quote", '"').option("escape", '"').csv(path)
    cols = d.columns
    rest = [c for i, c in enumerate(cols) if i not in (geometry, uri)]
    attrs = F.create_map(*(x for c in rest for x in (F.lit(c), F.col(f"`{c}`")))) if rest else F.expr(_NONE)
    return _parsed(d, F.lit(None) if uri is None else F.col(f"`{cols[uri]}`"), F.col(f"`{cols[geometry]}`"), F.concat_ws(sep, *(F.col(f"`{c}`") for c in cols)), attrs)


def read_tsv(spark: SparkSession, path: str, **options) -> DataFrame:
    return read_csv(spark, path, sep="\t", **options)


def read_geojson(spark: SparkSession, path: str) -> DataFrame:
    """FeatureCollections (a file each) or one feature a line: one row a feature."""
    schema = "type string, id string, features array<string>, geometry string, properties map<string,string>"
    d = spark.read.text(path, wholetext=False).select("value")
    d = d.select(F.from_json("value", schema).alias("j"), "value")
    many = d.where("j.features is not null").select(F.explode("j.features").alias("value"))
    one = d.where("j.features is null").select("value")
    d = many.unionByName(one)
    feature = F.from_json("value", "id string, geometry struct<type:string,coordinates:string>, properties map<string,string>")
    d = d.select("value", feature.alias("f")).select("value", "f.*")
    # [[x,y],[x,y]] becomes (x y, x y), at every level of nesting.
    c = F.regexp_replace(F.col("geometry.coordinates"), r"\s+", "")
    c = F.regexp_replace(c, rf"\[({_NUMBER}),({_NUMBER})(?:,{_NUMBER})*\]", "$1 $2")
    c = F.translate(c, "[]", "()")
    return _parsed(d, F.col("id"), F.concat(F.upper(F.col("geometry.type")), F.lit(" "), c), F.col("value"), F.col("properties"))


def read_ntriples(spark: SparkSession, path: str) -> DataFrame:
    """Triples whose object is a WKT literal."""
    d = spark.read.text(path)
    pattern = r'^\s*<([^>]*)>\s+<([^>]*)>\s+"((?:[^"\\]|\\.)*)"(?:\^\^<([^>]*)>)?\s*\.\s*$'
    d = d.select("value", *(F.regexp_extract("value", pattern, k).alias(c) for k, c in ((1, "s"), (2, "p"), (3, "o"), (4, "t"))))
    d = d.where(F.col("p").endswith("asWKT") | F.col("t").endswith("wktLiteral") | (F.col("p") == ""))
    return _parsed(d, F.nullif(F.col("s"), F.lit("")), F.nullif(F.regexp_replace("o", r"^<[^>]*>\s*", ""), F.lit("")), F.col("value"))


def read_json_rdf(spark: SparkSession, path: str) -> DataFrame:
    """RDF as JSON, {subject: {predicate: [{value, type, datatype}]}}, one object a line."""
    d = spark.read.text(path)
    one = F.from_json("value", "map<string,map<string,array<struct<value:string,type:string,datatype:string>>>>")
    d = d.select("value", F.explode_outer(one).alias("s", "ps")).select("value", "s", F.explode_outer("ps").alias("p", "os")).select("value", "s", "p", F.explode_outer("os").alias("o"))
    return _parsed(d.where(F.col("p").endswith("asWKT") | F.col("p").isNull()), F.col("s"), F.regexp_replace("o.value", r"^<[^>]*>\s*", ""), F.col("value"))


class _Pages(InputPartition):
    def __init__(self, offset: int, limit: int):
        self.offset, self.limit = offset, limit


class _EndpointReader(DataSourceReader):
    def __init__(self, options):
        self.query, self.pages, self.size = options["query"], int(options.get("pages", 1)), int(options.get("page_size", 1000))
        name, _, attribute = options["fetcher"].partition(":")
        self.name, self.attribute, self.endpoint = name, attribute, options.get("endpoint", "")

    def partitions(self):
        return [_Pages(i * self.size, self.size) for i in range(self.pages)]

    def read(self, partition):
        import importlib

        fetch: Callable[[str, str], str] = getattr(importlib.import_module(self.name), self.attribute)
        answer = fetch(self.endpoint, f"{self.query} LIMIT {partition.limit} OFFSET {partition.offset}")
        for b in json.loads(answer)["results"]["bindings"]:
            yield (b["s"]["value"], b["wkt"]["value"])


class EndpointSource(DataSource):
    """A query endpoint, a page a partition; `fetcher` names a function (endpoint, query) -> result JSON."""

    @classmethod
    def name(cls):
        return "wkt_endpoint"

    def schema(self):
        return "uri string, wkt string"

    def reader(self, schema):
        return _EndpointReader(self.options)


def read_endpoint(spark: SparkSession, query: str, fetcher: str, endpoint: str = "", pages: int = 1, page_size: int = 1000) -> DataFrame:
    spark.dataSource.register(EndpointSource)
    d = spark.read.format("wkt_endpoint").options(query=query, fetcher=fetcher, endpoint=endpoint, pages=str(pages), page_size=str(page_size)).load()
    return _parsed(d, F.col("uri"), F.col("wkt"), F.concat_ws(" ", "uri", "wkt"))


def read_endpoint_batches(requests: DataFrame, fetcher: str, endpoint: str = "") -> DataFrame:
    """The answers to many requests (a column text), which the tasks send: an input's rows can so be asked for in batches."""
    name, _, attribute = fetcher.partition(":")

    def run(batches):
        import importlib

        import pyarrow as pa

        fetch: Callable[[str, str], str] = getattr(importlib.import_module(name), attribute)
        for b in batches:
            for text in b.column("text").to_pylist():
                found = json.loads(fetch(endpoint, text))["results"]["bindings"]
                yield pa.RecordBatch.from_arrays([pa.array([r[k]["value"] for r in found], pa.string()) for k in ("s", "wkt")], names=["uri", "wkt"])

    d = requests.select("text").mapInArrow(run, "uri string, wkt string")
    return _parsed(d, F.col("uri"), F.col("wkt"), F.concat_ws(" ", "uri", "wkt"))


def read_layer(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def _rings(body: Column) -> Column:
    """array<array<struct x,y>> of '(x y, x y), (…)' or 'x y, x y'."""
    flat = F.regexp_replace(F.regexp_replace(body, r"^\s*\(|\)\s*$", ""), r"\)\s*,\s*\(", ";")
    point = lambda p: F.struct(F.try_element_at(F.split(F.trim(p), r"\s+"), F.lit(1)).try_cast("double").alias("x"), F.try_element_at(F.split(F.trim(p), r"\s+"), F.lit(2)).try_cast("double").alias("y"))
    return F.transform(F.split(flat, ";"), lambda r: F.transform(F.split(r, ","), point))


def clean(parsed: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(good, rejected): canonical columns with a hash of the text as gid, and (reason, line).

    Repeated points are dropped and rings oriented (shell against the clock, holes with it); what cannot be
    repaired is rejected: parse errors, other types, bad numbers, fewer than two points, open or flat rings.
    """
    kind = F.upper(F.regexp_extract("wkt", r"^\s*([A-Za-z]+)", 1))
    body = F.regexp_extract("wkt", r"^\s*[A-Za-z]+\s*\((.*)\)\s*$", 1)
    d = parsed.select("*", kind.alias("kind"), body.alias("body"))
    d = d.withColumn("rings", F.when(F.col("body") != "", _rings(F.col("body"))))
    zero = F.array().cast("array<struct<x:double,y:double>>")
    last = lambda a: F.try_element_at(a, F.lit(-1))
    d = d.withColumn("rings", F.transform("rings", lambda r: F.aggregate(r, zero, lambda a, p: F.when(last(a).eqNullSafe(p), a).otherwise(F.concat(a, F.array(p))))))
    bad = F.exists("rings", lambda r: F.exists(r, lambda p: p["x"].isNull() | p["y"].isNull() | F.isnan(p["x"]) | F.isnan(p["y"]) | (F.abs(p["x"]) == float("inf")) | (F.abs(p["y"]) == float("inf"))))
    legs = lambda r: F.when(F.size(r) > 1, F.sequence(F.lit(0), F.size(r) - 2)).otherwise(F.array().cast("array<int>"))
    area = lambda r: F.aggregate(F.transform(legs(r), lambda i: F.get(r, i)["x"] * F.get(r, i + 1)["y"] - F.get(r, i + 1)["x"] * F.get(r, i)["y"]), F.lit(0.0), lambda a, b: a + b)
    polygon = F.col("kind") == "POLYGON"
    reason = (
        F.when(F.col("wkt").isNull() | (F.col("kind") == "") | ~F.col("wkt").rlike(r"^\s*[A-Za-z]+\s*(\(|EMPTY)"), "parse_error")
        .when(~F.col("kind").isin("LINESTRING", "POLYGON"), "unsupported_type")
        .when(F.col("rings").isNull(), "parse_error")
        .when(bad, "bad_number")
        .when(F.exists("rings", lambda r: F.size(r) < 2), "too_few_points")
        .when(polygon & F.exists("rings", lambda r: (F.size(r) < 4) | (F.get(r, F.lit(0)) != last(r))), "open_ring")
        .when(polygon & F.exists("rings", lambda r: area(r) == 0), "flat_ring")
    )
    d = d.withColumn("reason", reason)
    rejected = d.where("reason is not null").select("reason", "line")
    turned = F.when(polygon, F.transform("rings", lambda r, i: F.when((area(r) > 0) == (i == 0), r).otherwise(F.reverse(r)))).otherwise(F.col("rings"))
    good = d.where("reason is null").withColumn("rings", turned)
    points = F.flatten("rings")
    ends = F.aggregate("rings", F.array().cast("array<int>"), lambda a, r: F.concat(a, F.array(F.coalesce(last(a), F.lit(0)) + F.size(r))))
    good = good.select(
        F.xxhash64(F.coalesce("uri", F.lit("")), "wkt").alias("gid"), "uri", F.when(polygon, "P").otherwise("L").alias("geom_type"), F.when(polygon, 2).otherwise(1).cast("tinyint").alias("dim"),
        F.transform(points, lambda p: p["x"]).alias("xs"), F.transform(points, lambda p: p["y"]).alias("ys"), ends.alias("ring_ends"), "attrs",
    )
    return with_mbr(good), rejected


def write_links(links: DataFrame, path: str, form: str = "parquet", base: str = "http://example.org/relation#") -> None:
    """Links (sid, relation, tid, and suri, turi for triples) as Parquet by relation, CSV, or N-Triples."""
    if form == "parquet":
        links.write.partitionBy("relation").parquet(path)
    elif form == "csv":
        links.write.option("header", True).csv(path)
    elif form == "ntriples":
        links.select(F.format_string(f"<%s> <{base}%s> <%s> .", "suri", "relation", "turi").alias("value")).write.text(path)
    else:
        raise ValueError(form)


def append_run(spark: SparkSession, path: str, report: dict) -> None:
    """Adds a run's report (method, parameters, steps and measures) to the runs table."""
    rows = [(report["method"], {k: str(v) for k, v in report.get("params", {}).items()}, {k: float(v) for k, v in report.get("measures", {}).items()})]
    spark.createDataFrame(rows, "method string, params map<string,string>, measures map<string,double>").write.mode("append").parquet(path)


def compare_runs(spark: SparkSession, path: str) -> DataFrame:
    """Runs side by side: one row per method and measure, mean of its repetitions."""
    d = spark.read.parquet(path).select("method", F.explode("measures").alias("measure", "value"))
    return d.groupBy("method", "measure").agg(F.count(F.lit(1)).alias("runs"), F.avg("value").alias("mean"))
