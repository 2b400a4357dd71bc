"""Command line: catalogue, preview of an input, links of two files, comparison of methods on the given tables."""

from __future__ import annotations

import argparse
import json


def _read(spark, path: str, kind: str):
    from spatial_links.sources import readers as R

    if kind == "parquet":
        return R.read_layer(spark, path), None
    read = {"wkt": R.read_wkt, "csv": R.read_csv, "tsv": R.read_tsv, "geojson": R.read_geojson, "ntriples": R.read_ntriples, "json-rdf": R.read_json_rdf}[kind]
    return R.clean(read(spark, path))


def main(argv: list[str] | None = None) -> None:
    parser = argparse.ArgumentParser(prog="spatial_links")
    sub = parser.add_subparsers(dest="what", required=True)
    sub.add_parser("catalog")
    kinds = ("parquet", "wkt", "csv", "tsv", "geojson", "ntriples", "json-rdf")
    preview = sub.add_parser("preview")
    preview.add_argument("path")
    preview.add_argument("--format", default="parquet", choices=kinds)
    link = sub.add_parser("link")
    for a in ("source", "target", "output"):
        link.add_argument(a)
    link.add_argument("--format", default="parquet", choices=kinds)
    link.add_argument("--method", default="distributed_grid")
    link.add_argument("--params", default="{}", help="JSON object of parameters")
    link.add_argument("--relations", default="", help="comma-separated; all by default")
    link.add_argument("--output-format", default="parquet", choices=("parquet", "csv"))
    compare = sub.add_parser("compare")
    compare.add_argument("tables")
    compare.add_argument("--pair", default="p1")
    compare.add_argument("--runs", help="table that the reports are added to")
    a = parser.parse_args(argv)

    from pyspark.sql import SparkSession

    from spatial_links.plans import experiments, methods
    from spatial_links.sources import layers, readers

    spark = SparkSession.builder.getOrCreate()
    if a.what == "catalog":
        methods.methods_catalog(spark).show(200, truncate=False)
    elif a.what == "preview":
        good, bad = _read(spark, a.path, a.format)
        good.drop("xs", "ys").show(20, truncate=80)
        if bad is not None:
            bad.groupBy("reason").count().show()
    elif a.what == "link":
        (s, _), (t, _) = _read(spark, a.source, a.format), _read(spark, a.target, a.format)
        wanted = tuple(r for r in a.relations.split(",") if r) or None
        found = methods.discover_links(s, t, methods.MethodSpec(a.method, json.loads(a.params)), wanted)
        readers.write_links(found, a.output, a.output_format)
    else:
        s, t = layers.pair(spark, a.tables, a.pair)
        for name, spec in experiments.PARALLEL.items():
            report = experiments.run_report(s, t, spec)
            print(name, json.dumps(report["measures"]))
            if a.runs:
                readers.append_run(spark, a.runs, report)


if __name__ == "__main__":
    main()
