"""The registered queries of the engine: every method, variant, baseline, measure and workload, with SQL oracles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from spatial_links.functions import geometry as G
from spatial_links.operators import grid, measures, partitioned, schedule, verify, weights
from spatial_links.plans import methods as M
from spatial_links.plans import oracles as O
from spatial_links.plans.methods import MethodSpec
from spatial_links.plans.shared import new_path, settled, written
from spatial_links.sources import layers as L

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if oracle is not None:
            ORACLES[name] = oracle
        return f

    return add


def _big(df: DataFrame, *cols: str) -> list:
    return [F.col(c).cast("bigint").alias(c) for c in cols]


def _bigs(*cols: str) -> str:
    return ", ".join(f"cast({c} as bigint) as {c}" for c in cols)


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def _tagged(sql: dict[str, str], column: str = "pair") -> str:
    return " union all ".join(f"select '{k}' as {column}, * from ({q})" for k, q in sql.items())


def _related(m: DataFrame):
    return verify.relation("intersects", F.col("matrix"), F.col("s_dim"), F.col("t_dim"))


# Layers and geometry functions


def _layer_query(name: str) -> None:
    @query(f"q_layer_{name}", f"with {O.BASE}, l as ({O.layer(name)}) select gid, {_bigs('x', 'y', 'w', 'h')}, shape from l")
    def run(spark, sf_dir):
        d = L.layer(spark, sf_dir, name)
        return d.select("gid", *_big(d, "x", "y", "w", "h"), "shape")


for _name in (*L.RECIPES, "mixed"):
    _layer_query(_name)

_ROUTES = """with p as (select l_orderkey, l_partkey // 4 as x, date_diff('day', date '1995-01-01', cast(l_shipdate as date)) // 14 as y, min((l_shipdate, l_linenumber)) as f
  from lineitem group by 1, 2, 3),
r as (select l_orderkey as gid, count(*) as npoints, list({'x': x, 'y': y} order by f, x, y) as pts from p group by 1 having count(*) >= 2)"""


@query("q_layer_routes", _ROUTES + " select gid, npoints, array_to_string([cast(q.x as varchar) || ' ' || cast(q.y as varchar) for q in pts], ',') as points from r")
def layer_routes(spark, sf_dir):
    d = L.routes(spark, sf_dir)
    points = F.array_join(F.transform(F.arrays_zip("xs", "ys"), lambda p: F.concat_ws(" ", p["xs"].cast("int").cast("string"), p["ys"].cast("int").cast("string"))), ",")
    return d.select("gid", F.col("npoints").cast("bigint").alias("npoints"), points.alias("points"))


_ZONES = "select s_suppkey as gid, (s_suppkey * 37) % 480 as x, (s_suppkey * 53) % 700 as y, 20 as w, 24 as h from supplier"
_VISITS = "select event_id as gid, ts, user_id, event_type, cast(trunc(value) as bigint) as x, date_diff('second', timestamp '2024-01-01', ts) // 3600 as y, 1 + event_id % 10 as w, 0 as h from events"


@query("q_layer_zones", f"select gid, {_bigs('x', 'y', 'w', 'h')} from ({_ZONES})")
def layer_zones(spark, sf_dir):
    d = L.zones(spark, sf_dir)
    return d.select("gid", *_big(d, "x", "y", "w", "h"))


@query("q_layer_visits", f"select gid, {_bigs('x', 'y', 'w', 'h')} from ({_VISITS})")
def layer_visits(spark, sf_dir):
    d = L.visits(spark, sf_dir)
    return d.select("gid", *_big(d, "x", "y", "w", "h"))


@query("q_layer_triangles", "select vec_id as gid, " + ", ".join(f"cast(round(cast(embedding[{2 * i + k + 1}] as double) * 1000) as bigint) as {c}{i}" for i in range(3) for k, c in enumerate("xy")) + " from embeddings")
def layer_triangles(spark, sf_dir):
    return L.triangles(spark, sf_dir).select("gid", *(F.get(f"{c}s", F.lit(i)).cast("bigint").alias(f"{c}{i}") for i in range(3) for c in "xy"))


@query("q_mbr_of_points", _ROUTES + " select gid, " + ", ".join(f"cast(list_{f}([q.{a} for q in pts]) as bigint) as {a}{f}" for f in ("min", "max") for a in "xy") + " from r")
def mbr_of_points(spark, sf_dir):
    d = L.routes(spark, sf_dir)
    return d.select("gid", *_big(d, "xmin", "ymin", "xmax", "ymax"))


_MEASURED = {n: f"with {O.BASE}, l as ({O.layer(n)}), c as ({O.cells('l')}) select gid, cast(count(*) filter (where d = 2) as bigint) as area, cast(count(*) filter (where d = 1 and (is_line or inner_ = 0)) as bigint) as length from c join (select gid, is_line from l) using (gid) group by gid" for n in ("lakes", "streams")}


@query("q_geom_measures", _tagged(_MEASURED, "layer"))
def geom_measures(spark, sf_dir):
    return _union([L.layer(spark, sf_dir, n).select(F.lit(n).alias("layer"), "gid", G.area().cast("bigint").alias("area"), G.length().cast("bigint").alias("length")) for n in ("lakes", "streams")])


@query("q_range_window", f"with {O.BASE}, l as ({O.layer('parks')}) select gid from l where x <= 120 and x + w >= 100 and y <= 90 and y + h >= 60")
def range_window(spark, sf_dir):
    return L.layer(spark, sf_dir, "parks").where(G.in_window(100.0, 60.0, 120.0, 90.0)).select("gid")


# Sources


_LINES = r"\r\n|\n|\r"
_JUNK = f"select unnest(string_split_regex(text, '{_LINES}')) as line from documents"
_KIND = r"upper(regexp_extract(line, '^\s*([A-Za-z]+)', 1))"


@query("q_clean_report", f"""with {O.BASE}, j as ({_JUNK}), r as (select case when {_KIND} = '' or not regexp_matches(line, '^\\s*[A-Za-z]+\\s*(\\(|EMPTY)') then 'parse_error'
  when {_KIND} not in ('LINESTRING', 'POLYGON') then 'unsupported_type' else 'other' end as reason from j)
select 'accepted' as reason, count(*) as n from ({O.layer('lakes')}) union all select reason, count(*) as n from r group by 1""")
def clean_report(spark, sf_dir):
    """The lakes among all lines of all documents, as one file of lines to be cleaned."""
    from spatial_links.sources import readers as R

    path = new_path(spark, "wkt")
    junk = L.table(spark, sf_dir, "documents").select(F.explode(F.split("text", _LINES)).alias("value"))
    L.layer(spark, sf_dir, "lakes").select(G.to_wkt().alias("value")).unionByName(junk).write.text(path)
    good, rejected = R.clean(R.read_wkt(spark, path))
    good = good.groupBy().agg(F.count(F.lit(1)).alias("n")).select(F.lit("accepted").alias("reason"), "n")
    return good.unionByName(rejected.groupBy("reason").agg(F.count(F.lit(1)).alias("n")))


def _round_trip(name: str, layer: str, write, read) -> None:
    sql = f"with {O.BASE}, l as ({O.layer(layer)}) select 'urn:{layer}:' || gid as uri, cast(case shape when 'rect' then 5 when 'L' then 7 when 'ring' then 10 when 'hook' then 3 else 2 end as bigint) as npoints, cast(x as bigint) as xmin, cast(y as bigint) as ymin, cast(x + w as bigint) as xmax, cast(y + h as bigint) as ymax from l"

    @query(name, sql)
    def run(spark, sf_dir):
        from spatial_links.sources import readers as R

        path = new_path(spark, layer)
        write(L.layer(spark, sf_dir, layer).select("uri", G.to_wkt().alias("wkt"), "geom_type", "xs", "ys", "ring_ends"), path)
        good, _ = R.clean(read(R, spark, path))
        return good.select("uri", *_big(good, "npoints", "xmin", "ymin", "xmax", "ymax"))


def _geojson(d: DataFrame, path: str) -> None:
    point = F.transform(F.arrays_zip("xs", "ys"), lambda p: F.array(p["xs"], p["ys"]))
    starts = F.concat(F.array(F.lit(0)), F.slice("ring_ends", 1, F.size("ring_ends") - 1))
    rings = F.transform(F.arrays_zip(starts.alias("a"), F.col("ring_ends").alias("b")), lambda r: F.slice(point, r["a"] + 1, r["b"] - r["a"]))
    body = F.when(F.col("geom_type") == "L", F.format_string('{"type":"LineString","coordinates":%s}', F.to_json(F.get(rings, F.lit(0))))).otherwise(F.format_string('{"type":"Polygon","coordinates":%s}', F.to_json(rings)))
    d.select(F.format_string('{"type":"Feature","id":"%s","geometry":%s,"properties":{"k":"v"}}', "uri", body).alias("value")).write.text(path)


def _json_rdf(d: DataFrame, path: str) -> None:
    d.select(F.format_string('{"%s":{"http://www.opengis.net/ont/geosparql#asWKT":[{"value":"%s","type":"literal","datatype":"wktLiteral"}]}}', "uri", "wkt").alias("value")).write.text(path)


def _triples(d: DataFrame, path: str) -> None:
    d.select(F.format_string('<%s> <http://www.opengis.net/ont/geosparql#asWKT> "%s"^^<http://www.opengis.net/ont/geosparql#wktLiteral> .', "uri", "wkt").alias("value")).write.text(path)


_csv = lambda sep: lambda d, path: d.select("uri", "wkt").write.option("header", True).option("sep", sep).csv(path)
_round_trip("q_wkt_roundtrip", "lakes", _csv(";"), lambda R, spark, path: R.read_csv(spark, path, sep=";", geometry=1, uri=0))
_round_trip("q_csv_read", "streams", _csv(","), lambda R, spark, path: R.read_csv(spark, path, geometry=1, uri=0))
_round_trip("q_tsv_read", "streams", _csv("\t"), lambda R, spark, path: R.read_tsv(spark, path, geometry=1, uri=0))
_round_trip("q_geojson_roundtrip", "lakes", _geojson, lambda R, spark, path: R.read_geojson(spark, path))
_round_trip("q_ntriples_roundtrip", "lakes", _triples, lambda R, spark, path: R.read_ntriples(spark, path))
_round_trip("q_jsonrdf_read", "streams", _json_rdf, lambda R, spark, path: R.read_json_rdf(spark, path))


@query("q_sparql_read", f"with {O.BASE}, l as ({O.layer('lakes')}) select 'urn:lakes:' || gid as uri, cast(x as bigint) as xmin, cast(x + w as bigint) as xmax from l")
def sparql_read(spark, sf_dir):
    """The lakes asked of the stand-in endpoint, the rows of a hundred orders a query."""
    from spatial_links.sources import readers as R

    one = F.format_string('(<%s> "%s")', "uri", "wkt")
    d = L.layer(spark, sf_dir, "lakes").select("gid", "uri", G.to_wkt().alias("wkt"))
    d = d.groupBy(F.expr("gid div 800").alias("batch")).agg(F.concat_ws(" ", F.collect_list(one)).alias("values"))
    requests = d.select(F.format_string("SELECT ?s ?wkt WHERE { VALUES (?s ?wkt) { %s } }", "values").alias("text"))
    good, _ = R.clean(R.read_endpoint_batches(requests, "spatial_links.sources.local_endpoint:values"))
    return good.select("uri", *_big(good, "xmin", "xmax"))


# Tiles


def _tile_sql(*sides: str) -> str:
    return f"with {O.BASE}, s as ({O.layer('lakes')}), t as ({O.layer('streams')}), {O.tile(*sides)} select cast(round(tw * 1e6) as bigint) as w, cast(round(th * 1e6) as bigint) as h from tile"


def _tile_row(spark, tile: grid.Tile) -> DataFrame:
    return spark.range(1).select(F.lit(round(tile.w * 1e6)).cast("bigint").alias("w"), F.lit(round(tile.h * 1e6)).cast("bigint").alias("h"))


@query("q_grid_size_source", _tile_sql("s"))
def grid_size_source(spark, sf_dir):
    return _tile_row(spark, grid.mean_tile(L.pair(spark, sf_dir, "p1")[0]))


@query("q_grid_size_both", _tile_sql("s", "t"))
def grid_size_both(spark, sf_dir):
    return _tile_row(spark, grid.mean_tile(*L.pair(spark, sf_dir, "p1")))


_RANGES = "cast(floor(x / tw) as bigint) as x1, cast(floor((x + w) / tw) as bigint) as x2, cast(floor(y / th) as bigint) as y1, cast(floor((y + h) / th) as bigint) as y2"


@query("q_tiles_per_geometry", _tagged({p: f"with {O.BASE}, s as ({O.layer(L.PAIRS[p][0])}), t as ({O.layer(L.PAIRS[p][1])}), {O.tile('s')}, b as (select 'source' as side, * from s union all select 'target' as side, * from t), r as (select side, {_RANGES} from b, tile) select side, cast(sum((x2 - x1 + 1) * (y2 - y1 + 1)) as bigint) as tiles, count(*) as geometries from r group by side" for p in ("p1", "p2")}))
def tiles_per_geometry(spark, sf_dir):
    out = []
    for p in ("p1", "p2"):
        s, t = L.pair(spark, sf_dir, p)
        tile = grid.mean_tile(s)
        for side, d in (("source", s), ("target", t)):
            out.append(d.agg(F.sum(grid.tiles_each(d, tile)).cast("bigint").alias("tiles"), F.count(F.lit(1)).alias("geometries")).select(F.lit(p).alias("pair"), F.lit(side).alias("side"), "tiles", "geometries"))
    return _union(out)


@query("q_tile_load", f"with {O.BASE}, s as ({O.layer('lakes')}), {O.tile('s')}, r as (select gid, {_RANGES} from s, tile), e as (select gid, y1, y2, unnest(range(x1, x2 + 1)) as tx from r), f as (select gid, tx, unnest(range(y1, y2 + 1)) as ty from e) select tx, ty, count(*) as n from f group by tx, ty")
def tile_load(spark, sf_dir):
    s = L.layer(spark, sf_dir, "lakes")
    d = grid.dealt(grid.ranged(G.prefixed(s, "s", G.BOX), grid.mean_tile(s), "s"), "s")
    return d.groupBy("tx", "ty").agg(F.count(F.lit(1)).alias("n"))


# Candidates: every filter returns the same pairs

_PAIRS_P1 = O.pairs("p1") + " select sid, tid from c"


def _candidates(name: str, spec: MethodSpec, pair: str = "p1") -> None:
    @query(name, O.pairs(pair) + " select sid, tid from c")
    def run(spark, sf_dir):
        return M.candidate_pairs(*L.pair(spark, sf_dir, pair), spec).select("sid", "tid")


for _name, _spec in {
    "q_cand_two_grid": MethodSpec("two_sided_grid"),
    "q_cand_two_grid_static": MethodSpec("two_sided_grid", {"tile_w": 4.0, "tile_h": 3.0}),
    "q_cand_source_grid": MethodSpec("source_grid", {"broadcast_rows": 1_000_000}),
    "q_cand_source_grid_static": MethodSpec("source_grid", {"tile_w": 4.0, "tile_h": 3.0}),
    "q_cand_sweep_list": MethodSpec("plane_sweep_list"),
    "q_cand_sweep_stripes": MethodSpec("plane_sweep_stripes"),
    "q_cand_pbsm_list": MethodSpec("pbsm"),
    "q_cand_pbsm_stripes": MethodSpec("pbsm", {"structure": "stripes"}),
    "q_cand_stripe_hash": MethodSpec("stripe_hash"),
    "q_cand_stripe_str": MethodSpec("stripe_str"),
    "q_cand_rtree": MethodSpec("rtree"),
    "q_cand_quadtree": MethodSpec("quadtree"),
    "q_cand_crtree": MethodSpec("crtree"),
    "q_cand_brute": MethodSpec("brute_force"),
    "q_cand_dup_distinct": MethodSpec("two_sided_grid", {"dedup": "distinct"}),
    "q_cand_dup_group_by": MethodSpec("two_sided_grid", {"dedup": "group_by"}),
    "q_cand_dup_drop_duplicates": MethodSpec("two_sided_grid", {"dedup": "drop_duplicates"}),
    "q_cand_dup_reduce_by_key": MethodSpec("two_sided_grid", {"dedup": "reduce_by_key"}),
    "q_cand_original_two_grid": MethodSpec("two_sided_grid", {"dedup": "distinct", "swap": True}),
}.items():
    _candidates(_name, _spec)


@query("q_cand_serial_sweep", _PAIRS_P1)
def cand_serial_sweep(spark, sf_dir):
    """The one-task form of the plane sweep, for the like-for-like comparison."""
    return M.candidate_pairs(*L.pair(spark, sf_dir, "p1"), MethodSpec("plane_sweep_list", {"strips": 1})).select("sid", "tid")


_candidates("q_cand_sweep_window", MethodSpec("plane_sweep_stops"))


@query("q_cand_uri_ids", O.pairs("p1") + " select 'urn:lakes:' || sid as suri, 'urn:streams:' || tid as turi from c")
def cand_uri_ids(spark, sf_dir):
    """The baseline with text identifiers instead of integers."""
    s, t = (d.withColumn("gid", F.col("uri")) for d in L.pair(spark, sf_dir, "p1"))
    p = M.candidate_pairs(s, t, MethodSpec("two_sided_grid"))
    return p.select(F.col("sid").alias("suri"), F.col("tid").alias("turi"))


@query("q_cand_bloom", _PAIRS_P1)
def cand_bloom(spark, sf_dir):
    """The ablation with a Bloom filter of the sources' tiles, through which targets pass before they are dealt."""
    s, t = L.pair(spark, sf_dir, "p1")
    about = grid.stats(s)[0]
    return M.candidate_pairs(s, grid.TileFilter(s, about.tile(), about.rows).passed(t), MethodSpec("source_grid")).select("sid", "tid")


@query("q_cand_undeduped", O.scored("p1", "cf") + " select sid, tid, cast(k as bigint) as times from w")
def cand_undeduped(spark, sf_dir):
    s, t = L.pair(spark, sf_dir, "p1")
    d = grid.join_tiles(s, t, grid.mean_tile(s), own=False)
    return d.groupBy("sid", "tid").agg(F.count(F.lit(1)).alias("times"))


# Distributed joins: links


def _join(name: str, spec: MethodSpec, pair: str = "p1") -> None:
    @query(name, O.links(pair))
    def run(spark, sf_dir):
        return M.discover_links(*L.pair(spark, sf_dir, pair), spec)


for _name, _spec in {
    "q_join_kdb": MethodSpec("sampled_partition_join"),
    "q_join_kdb_nested": MethodSpec("sampled_partition_join", {"local": "nested"}),
    "q_join_quadtree_sample": MethodSpec("sampled_partition_join", {"partitioner": "quadtree", "local": "quadtree"}),
    "q_join_kdb_overflow": MethodSpec("sampled_partition_join", {"overflow": "bucket"}),
    "q_join_broadcast_rtree": MethodSpec("broadcast_join"),
    "q_join_fixed_grid": MethodSpec("partition_pair_join", {"nx": 128, "ny": 64}),
    "q_join_bsp": MethodSpec("partition_pair_join", {"partitioner": "bsp"}),
    "q_join_str": MethodSpec("partition_pair_join", {"partitioner": "str"}),
    "q_join_distributed_grid": MethodSpec("distributed_grid"),
    "q_join_distributed_grid_swapped": MethodSpec("distributed_grid", {"source": "right"}),
    "q_join_skew_grid": MethodSpec("skew_aware_join", {"partitioner": "grid", "local": "grid"}),
    "q_join_skew_rtree": MethodSpec("skew_aware_join", {"partitioner": "rtree"}),
    "q_join_skew_quadtree": MethodSpec("skew_aware_join", {"local": "quadtree"}),
    "q_join_zorder": MethodSpec("zorder_join", {"precision": 14}),
}.items():
    _join(_name, _spec)


_WALKS = f"""with p as (select l_orderkey, l_partkey // 4 as x, date_diff('day', date '1995-01-01', cast(l_shipdate as date)) // 14 as y, min((l_shipdate, l_linenumber)) as f
  from lineitem group by 1, 2, 3), r as (select l_orderkey as gid, list({{'x': x, 'y': y}} order by f, x, y) as pts from p group by 1 having count(*) >= 2),
u as (select gid, pts[1].x as fx, pts[1].y as fy, unnest(pts) as q from r), v as (select gid, fx + ((q.x - fx) % 24 + 24) % 24 as x, fy + ((q.y - fy) % 24 + 24) % 24 as y from u),
k as (select gid, min(x) as x1, min(y) as y1, max(x) as x2, max(y) as y2 from v group by 1 having count(distinct (x, y)) >= 2)"""


@query("q_cand_skew_walks", f"{_WALKS}, {O.BASE}, s as ({O.layer('lakes')}) select s.gid as sid, k.gid as tid from s join k on s.x <= x2 and x1 <= s.x + s.w and s.y <= y2 and y1 <= s.y + s.h")
def cand_skew_walks(spark, sf_dir):
    """Slanting lines of every order's stops over lakes: the skewed workload; candidates."""
    return M.candidate_pairs(L.layer(spark, sf_dir, "lakes"), L.layer(spark, sf_dir, "walks"), MethodSpec("skew_aware_join"))


@query("q_join_skew_walks")
def join_skew_walks(spark, sf_dir):
    """Relation counts of the skewed workload (slanting lines, so the lattice oracle has no truth; tested against the exact kernel)."""
    return verify.relation_counts(M.pair_matrices(L.layer(spark, sf_dir, "lakes"), L.layer(spark, sf_dir, "walks"), MethodSpec("skew_aware_join")))


for _p in L.PAIRS:
    _join(f"q_links_{_p}", MethodSpec("distributed_grid"), _p)


def _matrix(pair: str) -> None:
    @query(f"q_matrix_{pair}", O.matrices(pair))
    def run(spark, sf_dir):
        return M.pair_matrices(*L.pair(spark, sf_dir, pair)).select("sid", "tid", "matrix")


for _p in ("p1", "p3", "p5"):
    _matrix(_p)


def _one_relation(r: str) -> None:
    pair = {"crosses": "p4"}.get(r, "p3")

    @query(f"q_rel_{r}", f'{O.pair_ctes(pair)} select sid, tid from flags where "{r}"')
    def run(spark, sf_dir):
        return M.discover_links(*L.pair(spark, sf_dir, pair), "distributed_grid", (r,)).select("sid", "tid")


for _r in verify.RELATIONS:
    _one_relation(_r)


@query("q_rel_runs", O.links("p5"))
def rel_runs(spark, sf_dir):
    """The baseline of one run per relation, the whole work each time."""
    s, t = L.pair(spark, sf_dir, "p5")
    return verify.one_relation_runs(s, t, lambda a, b: grid.join_tiles(a, b, grid.mean_tile(a), carry=True).select("sid", "tid", *(p + c for p in ("s_", "t_") for c in ("dim", *G.SHAPE))))


@query("q_disjoint_counts", f'{O.pair_ctes("p1")}, n as (select sid, count(*) as n from flags where intersects group by 1) select s.gid as sid, (select count(*) from t) - coalesce(n.n, 0) as disjoint from s left join n on n.sid = s.gid')
def disjoint_counts(spark, sf_dir):
    """Closed world: how many targets each source has nothing in common with."""
    s, t = L.pair(spark, sf_dir, "p1")
    m = M.pair_matrices(s, t)
    return verify.disjoint_counts(s, t, m.where(_related(m)))


# Tables of relations


@query("q_relation_counts", _tagged({p: O.counts(p) for p in ("p1", "p2", "p3", "p4", "p5", "p6")}))
def all_relation_counts(spark, sf_dir):
    return _union([verify.relation_counts(M.pair_matrices(*L.pair(spark, sf_dir, p))).select(F.lit(p).alias("pair"), "relation", "pairs") for p in ("p1", "p2", "p3", "p4", "p5", "p6")])


def relation_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The flagship: the distributed grid join on the first pair."""
    return verify.relation_counts(M.pair_matrices(*L.pair(spark, sf_dir, "p1")))


QUERIES["q_flagship"], ORACLES["q_flagship"] = relation_counts, O.counts("p1")


def _kinds(spark, sf_dir) -> DataFrame:
    s, t = L.pair(spark, sf_dir, "p4")
    links = M.discover_links(s, t, relations=("touches", "crosses", "overlaps"))
    kind = lambda d, p: d.select(F.col("gid").alias(f"{p}id"), F.col("shape").alias(f"kind_{p}"))
    return links.join(kind(s, "s"), "sid").join(kind(t, "t"), "tid")


def _rollup_sql(group: str) -> str:
    parts = " union all ".join(f"select sid, tid, '{r}' as relation from flags where \"{r}\"" for r in ("touches", "crosses", "overlaps"))
    return f"{O.pair_ctes('p4')}, k as (select l.relation, s.shape as kind_s, t.shape as kind_t from ({parts}) l join s on s.gid = l.sid join t on t.gid = l.tid) select coalesce(kind_s, '*') as kind_s, coalesce(kind_t, '*') as kind_t, coalesce(relation, '*') as relation, count(*) as n from k group by {group}"


def _starred(d: DataFrame) -> DataFrame:
    star = lambda c: F.coalesce(F.col(c), F.lit("*")).alias(c)
    return d.select(star("kind_s"), star("kind_t"), star("relation"), "n")


@query("q_relation_rollup", _rollup_sql("rollup(kind_s, kind_t, relation)"))
def relation_rollup(spark, sf_dir):
    return _starred(_kinds(spark, sf_dir).rollup("kind_s", "kind_t", "relation").agg(F.count(F.lit(1)).alias("n")))


@query("q_relation_cube", _rollup_sql("cube(kind_s, kind_t, relation)"))
def relation_cube(spark, sf_dir):
    return _starred(_kinds(spark, sf_dir).cube("kind_s", "kind_t", "relation").agg(F.count(F.lit(1)).alias("n")))


@query("q_relation_grouping_sets", _rollup_sql("grouping sets ((kind_s, relation), (kind_t, relation), ())"))
def relation_grouping_sets(spark, sf_dir):
    d = _kinds(spark, sf_dir)
    k = [F.col(c) for c in ("kind_s", "kind_t", "relation")]
    return _starred(d.groupingSets([[k[0], k[2]], [k[1], k[2]], []], *k).agg(F.count(F.lit(1)).alias("n")))


@query("q_converse_check", "select unnest(['contains', 'covers']) as relation, cast(0 as bigint) as differences")
def converse_check(spark, sf_dir):
    s, t = L.pair(spark, sf_dir, "p3")
    out = []
    for r, back in (("contains", "within"), ("covers", "covered_by")):
        a = M.discover_links(s, t, relations=(r,)).select("sid", "tid")
        b = M.discover_links(t, s, relations=(back,)).select(F.col("tid").alias("sid"), F.col("sid").alias("tid"))
        out.append(a.exceptAll(b).unionByName(b.exceptAll(a)).agg(F.count(F.lit(1)).alias("differences")).select(F.lit(r).alias("relation"), "differences"))
    return _union(out)


@query("q_transpose_check", f"{O.pair_ctes('p3')} select count(*) as pairs, cast(0 as bigint) as wrong from c")
def transpose_check(spark, sf_dir):
    s, t = L.pair(spark, sf_dir, "p3")
    a = M.pair_matrices(s, t).select("sid", "tid", verify.transpose(F.col("matrix")).alias("m"))
    b = M.pair_matrices(t, s).select(F.col("tid").alias("sid"), F.col("sid").alias("tid"), F.col("matrix").alias("n"))
    return a.join(b, ["sid", "tid"]).agg(F.count(F.lit(1)).alias("pairs"), F.sum((F.col("m") != F.col("n")).cast("bigint")).alias("wrong"))


_IDENTITY = "intersects - touches - crosses - overlaps - contains - within + equals"


@query("q_relation_identity", _tagged({p: f"{O.pair_ctes(p)} select cast(sum(intersects::int - touches::int - crosses::int - \"overlaps\"::int - contains::int - within::int + equals::int) as bigint) as difference from flags" for p in ("p1", "p3", "p4", "p5")}))
def relation_identity(spark, sf_dir):
    out = []
    for p in ("p1", "p3", "p4", "p5"):
        m = verify.with_relations(M.pair_matrices(*L.pair(spark, sf_dir, p)))
        term = lambda r, k: k * F.col(r).cast("bigint")
        total = sum((term(r, k) for r, k in (("touches", -1), ("crosses", -1), ("overlaps", -1), ("contains", -1), ("within", -1), ("equals", 1))), F.col("intersects").cast("bigint"))
        out.append(m.agg(F.sum(total).alias("difference")).select(F.lit(p).alias("pair"), "difference"))
    return _union(out)


_SAME = ("source_grid", "pbsm", "crtree", "skew_aware_join")


@query("q_method_equivalence", f"{O.pairs('p1')} select m as method, cast(0 as bigint) as missing, cast(0 as bigint) as extra, (select count(*) from c) as common from (select unnest({list(_SAME)}) as m)")
def method_equivalence(spark, sf_dir):
    s, t = L.pair(spark, sf_dir, "p1")
    want = M.candidate_pairs(s, t, "distributed_grid").select("sid", "tid")
    n = lambda d, c: d.agg(F.count(F.lit(1)).alias(c))
    out = []
    for m in _SAME:
        got = M.candidate_pairs(s, t, m).select("sid", "tid")
        out.append(n(want.exceptAll(got), "missing").crossJoin(n(got.exceptAll(want), "extra")).crossJoin(n(got.intersect(want), "common")).select(F.lit(m).alias("method"), "missing", "extra", "common"))
    return _union(out)


# Weights and schedulers


def _p7(spark, sf_dir, pair: str = "p7", both: bool = False):
    """(pairs, tile, source, target) with the mean tile of the source, or of both sides."""
    s, t = L.pair(spark, sf_dir, pair)
    about = tuple(grid.stats(s, t))
    tile = (grid.joint(*about) if both else about[0]).tile()
    return grid.join_tiles(s, t, tile, about=about), tile, s, t


def _universe(s: DataFrame, t: DataFrame, tile: grid.Tile) -> int:
    r = s.select(*G.BOX).unionByName(t.select(*G.BOX)).agg(F.min("xmin"), F.max("xmax"), F.min("ymin"), F.max("ymax")).first()
    return int((r[1] // tile.w - r[0] // tile.w + 1) * (r[3] // tile.h - r[2] // tile.h + 1))


def _weight(scheme: str) -> None:
    @query(f"q_w_{scheme}", O.scored("p7", scheme) + " select sid, tid, round(weight, 6) as weight from w")
    def run(spark, sf_dir):
        pairs, tile, s, t = _p7(spark, sf_dir)
        n = _universe(s, t, tile) if scheme == "chi2" else 0
        return pairs.select("sid", "tid", F.round(weights.weight(scheme, n), 6).alias("weight"))


for _s in weights.SCHEMES:
    _weight(_s)


@query("q_w_composite", O.scored("p7", "js", "mbro") + ", rk as (select *, row_number() over (order by weight desc, second desc, sid, tid) as position, rank() over (order by weight desc, second desc) as rank, dense_rank() over (order by weight desc, second desc) as dense from w) select position, sid, tid, rank, dense from rk where position <= 100")
def w_composite(spark, sf_dir):
    pairs, *_ = _p7(spark, sf_dir)
    top = schedule.global_top(written(weights.scored(pairs, "js", "mbro")), 100)
    w = Window.partitionBy(F.lit(1)).orderBy(F.desc("weight"), F.desc("second"))  # at most 100 rows
    return top.select("position", "sid", "tid", F.rank().over(w).cast("bigint").alias("rank"), F.dense_rank().over(w).cast("bigint").alias("dense"))


@query("q_cf_counted", O.scored("p7", "cf") + " select sid, tid, cast(k as bigint) as n from w")
def cf_counted(spark, sf_dir):
    s, t = L.pair(spark, sf_dir, "p7")
    return grid.join_tiles(s, t, grid.mean_tile(s), own=False).groupBy("sid", "tid").agg(F.count(F.lit(1)).alias("n"))


_BU = "(select cast(ceil(0.1 * count(*)) as bigint) from w)"


def _top_sql(order: str, source: str = "w", extra: str = "") -> str:
    return f"{extra}, p as (select *, row_number() over (order by {order}) as position from {source}) select position, sid, tid from p where position <= {_BU}"


_BEST = "weight desc, second desc, sid, tid"


def _budget(scored: DataFrame) -> tuple[int, int]:
    n = scored.count()
    return schedule.Budget(fraction=0.1).pairs(n), n


def _sched(name: str, oracle: str | None, primary: str, secondary: str | None, order, both: bool = False) -> None:
    @query(name, oracle)
    def run(spark, sf_dir):
        pairs, *_ = _p7(spark, sf_dir, both=both)
        scored = written(weights.scored(pairs, primary, secondary, keep=("tx", "ty")))  # counted, cut to a quantile and numbered: read several times
        return order(scored, _budget(scored)[0]).select("position", "sid", "tid")


_ORDERED = O.scored("p7", "js", "mbro")
for _s in ("js", "mbro", "cf"):
    _sched(f"q_sched_global_{_s}", O.scored("p7", _s) + _top_sql(_BEST), _s, None, schedule.global_top)


def _geo(side: str) -> str:
    one = lambda s: f"select *, '{s}' as side, {'sid' if s == 'source' else 'tid'} as geo from w"
    return f", e as ({one('source') + ' union all ' + one('target') if side == 'both' else one(side)})"


def _local_sql(side: str) -> str:
    quota = f"(select greatest(1, cast(ceil({_BU} / cast((select count(*) from (select distinct side, geo from e)) as double)) as bigint)))"
    return _ORDERED + _geo(side) + f", k as (select distinct sid, tid, weight, second from (select *, row_number() over (partition by side, geo order by {_BEST}) as rk from e) where rk <= {quota})" + _top_sql(_BEST, "k")


def _geometry_sql(side: str) -> str:
    means = ", m as (select side, geo, round(avg(weight), 9) as mean from e group by 1, 2), j as (select e.*, mean from e join m using (side, geo))"
    one = ", g as (select sid, tid, weight, second, max((mean, side, geo)) as b from j group by 1, 2, 3, 4), j2 as (select sid, tid, weight, second, b[1] as mean, b[2] as side, b[3] as geo from g)"
    if side != "both":
        one = ", j2 as (select sid, tid, weight, second, mean, side, geo from j)"
    return _ORDERED + _geo(side) + means + one + f", h as (select *, row_number() over (order by mean desc, side, geo, {_BEST}) as q from j2), k as (select * from h where q <= {_BU})" + _top_sql(_BEST, "k")


def _robin_sql(side: str) -> str:
    means = f", m as (select side, geo, round(avg(weight), 9) as mean from e group by 1, 2), j as (select e.*, mean, row_number() over (partition by side, geo order by {_BEST}) as rd from e join m using (side, geo))"
    one = ", j2 as (select sid, tid, rd, mean, side, geo from j)"
    if side == "both":
        one = ", g as (select sid, tid, max((-rd, mean, side, geo)) as b from j group by 1, 2), j2 as (select sid, tid, -b[1] as rd, b[2] as mean, b[3] as side, b[4] as geo from g)"
    return _ORDERED + _geo(side) + means + one + _top_sql("rd, mean desc, side, geo, sid, tid", "j2")


for _side in ("target", "source", "both"):
    _suffix = "" if _side == "target" else f"_{_side}"
    _sched(f"q_sched_local{_suffix}", _local_sql(_side), "js", "mbro", lambda d, bu, side=_side: schedule.local_top(d, bu, side))
    _sched(f"q_sched_geometry{_suffix}", _geometry_sql(_side), "js", "mbro", lambda d, bu, side=_side: schedule.geometry_ordered(d, bu, side))
    _sched(f"q_sched_roundrobin{_suffix}", _robin_sql(_side), "js", "mbro", lambda d, bu, side=_side: schedule.round_robin(d, bu, side))
for _order, _dir in (("asc", ""), ("desc", " desc")):
    _sched(f"q_sched_tiles_{_order}", O.scored("p7", "js", "mbro", ("s", "t")) + ", k as (select *, count(*) over (partition by tx, ty) as n from w)" + _top_sql(f"n{_dir}, tx, ty, {_BEST}", "k"), "js", "mbro", lambda d, bu, o=_order: schedule.tile_ordered(d, bu, o), both=True)
_sched("q_sched_unordered", _ORDERED + _top_sql("(sid * 2654435761 + tid * 40503) % 1000003, sid, tid"), "js", "mbro", schedule.unordered)

# The parallel forms: every partition of the distributed grid applies the scheduler to its own pairs, within its part of the budget.
_SHARDS = 16
_SHARD = f"(tx * 31 + ty) % {_SHARDS}"
_PARTED = f""", g as (select *, (({_SHARD}) + {_SHARDS}) % {_SHARDS} as shard from w), n as (select shard, count(*) as c, count(distinct tid) as targets from g group by 1), b as (select {_BU} as bu, (select count(*) from w) as total),
f as (select shard, targets, bu * c // total as base, row_number() over (order by bu * c % total desc, shard) as place, bu from n, b),
qq as (select shard, targets, base + case when place <= bu - (select sum(base) from f) then 1 else 0 end as quota from f),
gq as (select g.*, quota, targets from g join qq using (shard))"""
_PART_ORDERS = {
    "global": ("gq", _BEST),
    "local": (f"(select * from (select *, row_number() over (partition by shard, tid order by {_BEST}) as rk from gq) where rk <= greatest(1, ceil(quota / targets)))", _BEST),
    "geometry": (f"(select * from (select *, row_number() over (partition by shard order by mean desc, tid, {_BEST}) as rk from (select *, round(avg(weight) over (partition by shard, tid), 9) as mean from gq)) where rk <= quota)", _BEST),
    "round_robin": (f"(select *, row_number() over (partition by shard, tid order by {_BEST}) as rk, round(avg(weight) over (partition by shard, tid), 9) as mean from gq)", "rk, mean desc, tid, sid"),
    "tiles": ("(select *, count(*) over (partition by shard, tx, ty) as n from gq)", f"n, tx, ty, {_BEST}"),
}


def _parted(order: str) -> None:
    rows, by = _PART_ORDERS[order]
    oracle = _ORDERED + _PARTED + f", z as (select shard, quota, sid, tid, row_number() over (partition by shard order by {by}) as position from {rows}) select cast(shard as bigint) as shard, position, sid, tid from z where position <= quota"

    @query("q_sched_sharded" if order == "global" else f"q_sched_sharded_{order}", oracle)
    def run(spark, sf_dir):
        pairs, *_ = _p7(spark, sf_dir)
        scored = written(weights.scored(pairs, "js", "mbro", keep=("tx", "ty")))
        return schedule.sharded(scored, _budget(scored)[0], schedule.tile_shard(_SHARDS), order).select(F.col("shard").cast("bigint").alias("shard"), "position", "sid", "tid")


for _order in _PART_ORDERS:
    _parted(_order)


def _verified(top: DataFrame, s: DataFrame, t: DataFrame) -> DataFrame:
    keep = [c for c in ("shard", "position", "sid", "tid", "weight", "second") if c in top.columns]
    m = verify.matrices(verify.attach(top.select(*keep), s, t))
    return m.select(*keep, _related(m).alias("related"))


def _dynamic(name: str, primary: str, secondary: str | None) -> None:
    @query(name)
    def run(spark, sf_dir):
        pairs, _, s, t = _p7(spark, sf_dir)
        scored = written(weights.scored(pairs, primary, secondary))
        top = schedule.global_top(scored, _budget(scored)[0])
        return schedule.dynamic_top(written(_verified(top, s, t))).select("position", "sid", "tid", "related")


_dynamic("q_sched_dynamic_js", "js", None)
_dynamic("q_sched_dynamic_mbro", "mbro", None)
_dynamic("q_sched_composite_dynamic", "js", "mbro")


@query("q_sched_dynamic_rounds")
def sched_dynamic_rounds(spark, sf_dir):
    """The global dynamic order in four rounds over the whole budget."""
    pairs, _, s, t = _p7(spark, sf_dir)
    scored = written(weights.scored(pairs, "js", "mbro"))
    budget = _budget(scored)[0]
    return schedule.dynamic_rounds(scored, lambda d: _verified(d, s, t), budget, max(1, -(-budget // 4))).select("position", "sid", "tid", "related")


@query("q_sched_dynamic_sharded")
def sched_dynamic_sharded(spark, sf_dir):
    pairs, _, s, t = _p7(spark, sf_dir)
    scored = written(weights.scored(pairs, "js", "mbro", keep=("tx", "ty")))
    top = schedule.sharded(scored, _budget(scored)[0], schedule.tile_shard(_SHARDS))
    return schedule.dynamic_top(_verified(top, s, t), shard=F.col("shard")).select("shard", "position", "sid", "tid", "related")


_SECONDS = (0, 3600)


def _with_flags(scored_sql: str, pair: str = "p7") -> str:
    """The weights' CTEs behind the flags' CTEs of the same pair."""
    tail = scored_sql.split("c as materialized", 1)[1].split(", tile as ", 1)[1]
    return f"{O.pair_ctes(pair)}, tile as {tail}"


@query("q_sched_time_budget", _with_flags(O.scored("p7", "js")) + f", i as (select intersects, row_number() over (order by {_BEST}) as position from w join flags using (sid, tid)) select cast(b as bigint) as seconds, cast(sum(case when b > 0 and position <= {_BU} then 1 else 0 end) as bigint) as verified, cast(sum(case when b > 0 and position <= {_BU} and intersects then 1 else 0 end) as bigint) as related from i, (values {', '.join(f'({x})' for x in _SECONDS)}) v(b) group by 1")
def sched_time_budget(spark, sf_dir):
    """The best pairs verified under a time limit: one that has run out, and one that all of a tenth meets."""
    pairs, _, s, t = _p7(spark, sf_dir)
    scored = written(weights.scored(pairs, "js"))
    top = written(schedule.global_top(scored, _budget(scored)[0]).select("position", "sid", "tid"))
    n = lambda d, b: d.agg(F.count(F.lit(1)).alias("verified"), F.coalesce(F.sum(F.col("related").cast("bigint")), F.lit(0)).alias("related")).select(F.lit(b).cast("bigint").alias("seconds"), "verified", "related")
    return _union([n(schedule.verified_within(top, s, t, b), b) for b in _SECONDS])


def _all_flagged(spark, sf_dir, pair: str = "p7"):
    """(pairs, related flags as a written table)"""
    pairs, _, s, t = _p7(spark, sf_dir, pair)
    m = M.pair_matrices(s, t)
    return pairs, written(m.select("sid", "tid", _related(m).alias("related")))


@query("q_sched_ideal", _with_flags(_ORDERED) + ", i as (select w.sid, w.tid, intersects from w join flags using (sid, tid))" + _top_sql("intersects desc, sid, tid", "i"))
def sched_ideal(spark, sf_dir):
    pairs, flags = _all_flagged(spark, sf_dir)
    scored = written(weights.scored(pairs, "js", "mbro"))
    return schedule.ideal(scored, flags, _budget(scored)[0]).select("position", "sid", "tid")


#: The pairs of the progressive comparison, and its static orders as SQL.
COMPARED = ("p2", "p7", "p8", "p9")
_STATIC = {
    "global_js": "js desc, sid, tid", "global_mbro": "mb desc, sid, tid", "composite": "js desc, mb desc, sid, tid",
    "unordered": "(sid * 2654435761 + tid * 40503) % 1000003, sid, tid", "ideal": "intersects desc, sid, tid",
}


def _eval_sql(pair: str) -> str:
    base = _with_flags(O.scored(pair, "js", "mbro"), pair)
    ranks = " union all ".join(f"select '{m}' as method, intersects, row_number() over (order by {o}) as position from z" for m, o in _STATIC.items())
    return f"""{base}, z as (select sid, tid, weight as js, second as mb, intersects from w join flags using (sid, tid)), ranked as materialized ({ranks}), total as (select count(*) as c, sum(intersects::int) as r from z),
bu as (select f / 20.0 as fraction, cast(ceil(f / 20.0 * c) as bigint) as budget, r from total, range(1, 11) g(f)),
hits as (select method, fraction, budget, any_value(r) as r, coalesce(sum(case when intersects and position <= budget then 1 else 0 end), 0) as found,
  coalesce(sum(case when intersects and position <= budget then budget - position + 1 else 0 end), 0) as area from ranked, bu group by 1, 2, 3),
m as (select *, least(budget, r) as best, found / budget as pr, found / least(budget, r) as re from hits)
select method, round(fraction, 2) as fraction, budget, cast(found as bigint) as found, round(pr, 6) as precision, round(re, 6) as recall, round(case when pr + re > 0 then 2 * pr * re / (pr + re) else 0 end, 6) as f_measure, cast(area as bigint) as area,
  round(area / (budget * best), 6) as unit, round(area / (best * (best + 1) / 2 + (budget - best) * best), 6) as ratio from m"""


def _rounded(m: DataFrame) -> DataFrame:
    return m.select("method", F.round("fraction", 2).alias("fraction"), "budget", "found", *(F.round(c, 6).alias(c) for c in ("precision", "recall", "f_measure")), "area", *(F.round(c, 6).alias(c) for c in ("unit", "ratio")))


def _evaluated(pair: str) -> None:
    @query(f"q_eval_budgets_{pair}", _eval_sql(pair))
    def static(spark, sf_dir):
        """Precision, recall, F and progressive recall at ten budgets, of the orders that verification does not change."""
        from spatial_links.plans import experiments as E

        return _rounded(E.progressive_comparison(spark, sf_dir, pair, tuple(_STATIC)))

    @query(f"q_eval_dynamic_{pair}")
    def dynamic(spark, sf_dir):
        """The same of the three dynamic orders, each budget being a run of its own."""
        from spatial_links.plans import experiments as E

        return _rounded(E.progressive_comparison(spark, sf_dir, pair, ("dynamic_js", "dynamic_mbro", "dynamic_composite")))


for _p in COMPARED:
    _evaluated(_p)


@query("q_eval_gaps", " union all ".join(f"select '{p}' as pair, e.method, round(avg(1 - e.recall), 4) as recall_gap, round(avg(1 - e.ratio), 4) as ratio_gap from ({_eval_sql(p)}) e where e.method <> 'ideal' group by 2" for p in ("p7", "p9")))
def eval_gaps(spark, sf_dir):
    """Mean distance from the ideal order over all budgets."""
    from spatial_links.plans import experiments as E

    orders = tuple(m for m in _STATIC if m != "ideal")  # its own gaps are none
    return _union([measures.mean_gaps(_rounded(E.progressive_comparison(spark, sf_dir, p, orders))).select(F.lit(p).alias("pair"), "method", F.round("recall_gap", 4).alias("recall_gap"), F.round("ratio_gap", 4).alias("ratio_gap")) for p in ("p7", "p9")])


@query("q_eval_curve", _with_flags(O.scored("p7", "mbro")) + f", rk as (select intersects, row_number() over (order by w.weight desc, w.sid, w.tid) as position from w join flags using (sid, tid)), st as (select cast(ceil(position / 1000.0) as bigint) as step, sum(intersects::int) as n, max(position) as position from rk where position <= {_BU} group by 1) select position, cast(sum(n) over (order by step) as bigint) as found from st")
def eval_curve(spark, sf_dir):
    pairs, flags = _all_flagged(spark, sf_dir)
    scored = written(weights.scored(pairs, "mbro"))
    ranked = schedule.global_top(scored, _budget(scored)[0]).join(flags, ["sid", "tid"])
    return measures.recall_curve(ranked.select("position", "related"), 1000)


# Workloads


@query("q_scalability_subsets", " union all ".join(f"select {k} as k, sources, targets, candidates, related from ({O.pair_ctes('p1').replace(', c as materialized (', f', s10 as (select * from s where (x // 10) % 10 < {k}), t10 as (select * from t where (x // 10) % 10 < {k}), c as materialized (').replace(O.candidates(), O.candidates('s10', 't10'))} select (select count(*) from s10) as sources, (select count(*) from t10) as targets, count(*) as candidates, count(*) filter (where intersects) as related from flags)" for k in range(1, 11)))
def scalability_subsets(spark, sf_dir):
    out = []
    for k in range(1, 11):
        s, t = (d.where(F.expr(f"(x div 10) % 10 < {k}")) for d in L.pair(spark, sf_dir, "p1"))
        m = M.pair_matrices(s, t)
        n = lambda d, c: d.agg(F.count(F.lit(1)).alias(c))
        links = m.agg(F.count(F.lit(1)).alias("candidates"), F.sum(_related(m).cast("bigint")).alias("related"))
        out.append(n(s, "sources").crossJoin(n(t, "targets")).crossJoin(links).select(F.lit(k).alias("k"), "sources", "targets", "candidates", "related"))
    return _union(out)


@query("q_qualifying_ratio", _tagged({p: f"{O.pair_ctes(p)} select count(*) as candidates, count(*) filter (where intersects) as related, round(count(*) filter (where intersects) / count(*), 6) as ratio from flags" for p in L.PAIRS}))
def qualifying_ratio(spark, sf_dir):
    out = []
    for p in L.PAIRS:
        m = M.pair_matrices(*L.pair(spark, sf_dir, p))
        d = m.agg(F.count(F.lit(1)).alias("candidates"), F.sum(_related(m).cast("bigint")).alias("related"))
        # One pair after another: what a pair's join shuffles need not lie there with that of the others.
        out.append(settled(d.select(F.lit(p).alias("pair"), "candidates", "related", F.round(F.col("related") / F.col("candidates"), 6).alias("ratio"))))
    return _union(out)


@query("q_relation_mix", _tagged({p: f"with n as ({O.counts(p)}) select relation, round(pairs / (select pairs from n where relation = 'intersects'), 6) as share from n" for p in ("p1", "p3")}))
def relation_mix(spark, sf_dir):
    out = []
    for p in ("p1", "p3"):
        n = verify.relation_counts(M.pair_matrices(*L.pair(spark, sf_dir, p)))
        all_ = n.where("relation = 'intersects'").select(F.col("pairs").alias("r"))
        out.append(n.crossJoin(all_).select(F.lit(p).alias("pair"), "relation", F.round(F.col("pairs") / F.col("r"), 6).alias("share")))
    return _union(out)


@query("q_reduction", _tagged({p: f"{O.pairs(p)} select (select count(*) from c) as candidates, (select count(*) from s) * (select count(*) from t) as cartesian" for p in ("p1", "p2", "p3")}))
def reduction(spark, sf_dir):
    out = []
    for p in ("p1", "p2", "p3"):
        s, t = L.pair(spark, sf_dir, p)
        n = lambda d, c: d.agg(F.count(F.lit(1)).alias(c))
        c = n(M.candidate_pairs(s, t), "candidates")
        out.append(c.crossJoin(n(s, "n")).crossJoin(n(t, "m")).select(F.lit(p).alias("pair"), "candidates", (F.col("n") * F.col("m")).alias("cartesian")))
    return _union(out)


@query("q_load_skew", f"with {O.BASE}, s as ({O.layer('lakes')}), {O.tile('s')}, r as (select gid, {_RANGES} from s, tile), e as (select gid, y1, y2, unnest(range(x1, x2 + 1)) as tx from r), f as (select gid, tx, unnest(range(y1, y2 + 1)) as ty from e), g as (select tx, ty, count(*) as n from f group by tx, ty) select count(*) as parts, min(n) as least, max(n) as most, round(avg(n), 6) as mean from g")
def load_skew(spark, sf_dir):
    s = L.layer(spark, sf_dir, "lakes")
    d = grid.dealt(grid.ranged(G.prefixed(s, "s", G.BOX), grid.mean_tile(s), "s"), "s")
    return measures.load_skew(d, ["tx", "ty"]).select("parts", "least", "most", F.round("mean", 6).alias("mean"))


@query("q_index_bytes")
def index_bytes(spark, sf_dir):
    """Bytes of the trees over the same sources, each cell's built where it lies."""
    return measures.index_bytes(L.layer(spark, sf_dir, "lakes"))


_RESIDENT = " union all ".join(f"select '{p}' as pair, * from (with {O.BASE}, s as ({O.layer(L.PAIRS[p][0])}), t as ({O.layer(L.PAIRS[p][1])}), k as (select (select sum({O.POINTS}) from s) as ps, (select count(*) from s) as ns, (select sum({O.POINTS}) from t) as pt, (select count(*) from t) as nt) select cast(least(48 * ns + 16 * ps, 48 * nt + 16 * pt) as bigint) as frugal, cast(48 * (ns + nt) + 16 * (ps + pt) as bigint) as intensive from k)" for p in ("p1", "p2", "p3"))


@query("q_memory_limit", _RESIDENT)
def memory_limit(spark, sf_dir):
    """Bytes that methods keep: of the smaller side if targets are read on the fly, of both if all is loaded."""
    return _union([measures.resident_bytes(*L.pair(spark, sf_dir, p)).select(F.lit(p).alias("pair"), "frugal", "intensive") for p in ("p1", "p2", "p3")])


# Joins around links, windows, attributes


def _relating(name: str, sql: str):
    return query(name, f"{O.pair_ctes('p1')}, l as (select sid, tid from flags where intersects) {sql}")


def _p1_related(spark, sf_dir):
    s, t = L.pair(spark, sf_dir, "p1")
    return s, t, M.discover_links(s, t, relations=("intersects",)).select("sid", "tid")


@_relating("q_semi_sources", "select gid from s where gid in (select sid from l)")
def semi_sources(spark, sf_dir):
    s, _, links = _p1_related(spark, sf_dir)
    return s.join(links, s.gid == links.sid, "left_semi").select("gid")


@_relating("q_anti_sources", "select gid from s where gid not in (select sid from l)")
def anti_sources(spark, sf_dir):
    s, _, links = _p1_related(spark, sf_dir)
    return s.join(links, s.gid == links.sid, "left_anti").select("gid")


@_relating("q_outer_counts", "select s.gid, count(l.tid) as links from s left join l on l.sid = s.gid group by s.gid")
def outer_counts(spark, sf_dir):
    s, _, links = _p1_related(spark, sf_dir)
    n = links.groupBy("sid").agg(F.count(F.lit(1)).alias("links"))
    return s.join(n, s.gid == n.sid, "left").select("gid", F.coalesce("links", F.lit(0)).alias("links"))


@query("q_self_join", f"{O.pair_ctes('lots:lots')} select sid, tid from flags where sid < tid and intersects")
def self_join(spark, sf_dir):
    d = L.layer(spark, sf_dir, "lots")
    m = M.pair_matrices(d, d)
    return m.where(_related(m) & (F.col("sid") < F.col("tid"))).select("sid", "tid")


@query("q_asof_visit", "select event_id, user_id, max(event_id) filter (where event_type = 'click') over w as last_click from events window w as (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding)".replace("max(event_id) filter (where event_type = 'click')", "last_value(case when event_type = 'click' then event_id end ignore nulls)"))
def asof_visit(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    d = L.table(spark, sf_dir, "events")
    return d.select("event_id", "user_id", F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w).alias("last_click"))


@query("q_topk_per_source", O.scored("p7", "mbro") + f", rk as (select sid, tid, row_number() over (partition by sid order by {_BEST}) as k from w) select sid, tid, k from rk where k <= 3")
def topk_per_source(spark, sf_dir):
    pairs, *_ = _p7(spark, sf_dir)
    k = F.row_number().over(Window.partitionBy("sid").orderBy(*schedule.best_first()))
    return weights.scored(pairs, "mbro").select("sid", "tid", k.cast("bigint").alias("k")).where("k <= 3")


@query("q_cand_percentiles", O.pairs("p1") + ", n as (select sid, count(*) as n from c group by 1) select round(quantile_cont(n, 0.5), 6) as p50, round(quantile_cont(n, 0.9), 6) as p90, max(n) as most from n")
def cand_percentiles(spark, sf_dir):
    n = M.candidate_pairs(*L.pair(spark, sf_dir, "p1")).groupBy("sid").agg(F.count(F.lit(1)).alias("n"))
    return n.agg(F.round(F.percentile("n", 0.5), 6).alias("p50"), F.round(F.percentile("n", 0.9), 6).alias("p90"), F.max("n").alias("most"))


@query("q_ntile_str", f"with {O.BASE}, l as ({O.layer('lakes')}) select gid, cast(ntile(4) over (partition by x // 50 order by y, gid) as bigint) as slice from l")
def ntile_str(spark, sf_dir):
    d = L.layer(spark, sf_dir, "lakes")
    return d.select("gid", F.ntile(4).over(Window.partitionBy(F.expr("x div 50")).orderBy("y", "gid")).cast("bigint").alias("slice"))


@query("q_lag_segments", _ROUTES + ", e as (select gid, unnest(range(1, npoints)) as i, pts from r) select gid, cast(i as bigint) as leg, cast(pts[i + 1].x - pts[i].x as bigint) as dx, cast(pts[i + 1].y - pts[i].y as bigint) as dy from e")
def lag_segments(spark, sf_dir):
    d = L.routes(spark, sf_dir).select("gid", F.posexplode(F.arrays_zip("xs", "ys")).alias("leg", "p"))
    w = Window.partitionBy("gid").orderBy("leg")
    d = d.select("gid", F.col("leg").cast("bigint").alias("leg"), (F.col("p.xs") - F.lag("p.xs").over(w)).cast("bigint").alias("dx"), (F.col("p.ys") - F.lag("p.ys").over(w)).cast("bigint").alias("dy"))
    return d.where("leg > 0")


@query("q_percent_rank_cut", O.scored("p7", "mbro") + ", rk as (select sid, tid, percent_rank() over (partition by tx order by weight desc, sid, tid) as pr from w) select sid, tid, round(pr, 6) as pr from rk where pr <= 0.1")
def percent_rank_cut(spark, sf_dir):
    pairs, *_ = _p7(spark, sf_dir)
    d = pairs.select("sid", "tid", "tx", weights.mbro().alias("weight"))
    pr = F.percent_rank().over(Window.partitionBy("tx").orderBy(F.desc("weight"), "sid", "tid"))
    return d.select("sid", "tid", F.round(pr, 6).alias("pr"), pr.alias("raw")).where("raw <= 0.1").drop("raw")


@query("q_links_json", f"{O.pair_ctes('p5')} select '{{\"sid\":' || sid || ',\"tid\":' || tid || '}}' as j from flags where equals")
def links_json(spark, sf_dir):
    d = M.discover_links(*L.pair(spark, sf_dir, "p5"), relations=("equals",))
    return d.select(F.to_json(F.struct("sid", "tid")).alias("j"))


@query("q_links_map", f"with {O.BASE}, l as ({O.layer('lakes')}) select gid, cast(orderkey as varchar) as orderkey from l")
def links_map(spark, sf_dir):
    d = L.layer(spark, sf_dir, "lakes")
    return d.select("gid", F.element_at(F.map_from_arrays(F.map_keys("attrs"), F.map_values("attrs")), "orderkey").alias("orderkey"))


@query("q_links_listed", f"{O.pair_ctes('p1')} select sid, array_to_string(list(tid order by tid), ',') as targets from flags where contains group by sid")
def links_listed(spark, sf_dir):
    d = M.discover_links(*L.pair(spark, sf_dir, "p1"), relations=("contains",))
    return d.groupBy("sid").agg(F.array_join(F.transform(F.sort_array(F.collect_list("tid")), lambda x: x.cast("string")), ",").alias("targets"))


@query("q_props", "select array_to_string(list_sort(json_keys(props)), ',') as keys, count(*) as n from events group by 1")
def props(spark, sf_dir):
    d = L.table(spark, sf_dir, "events").select("event_id", F.json_object_keys("props").alias("keys"))
    return d.groupBy(F.array_join(F.array_sort("keys"), ",").alias("keys")).agg(F.count(F.lit(1)).alias("n"))


@query("q_attr_join_nation", f"{O.pair_ctes('p1')} select n_name as nation, r_name as region, count(*) as links from flags f join s on s.gid = f.sid join orders on o_orderkey = s.orderkey join customer on c_custkey = o_custkey join nation on n_nationkey = c_nationkey join region on r_regionkey = n_regionkey where intersects group by 1, 2")
def attr_join_nation(spark, sf_dir):
    s, _, links = _p1_related(spark, sf_dir)
    key = s.select(F.col("gid").alias("sid"), F.col("attrs")["orderkey"].cast("bigint").alias("o_orderkey"))
    d = links.join(key, "sid").join(L.table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), "o_orderkey")
    d = d.join(L.table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_nationkey"), "o_custkey")
    d = d.join(L.table(spark, sf_dir, "nation").select(F.col("n_nationkey").alias("c_nationkey"), "n_name", "n_regionkey"), "c_nationkey").join(L.table(spark, sf_dir, "region").select(F.col("r_regionkey").alias("n_regionkey"), "r_name"), "n_regionkey")
    return d.groupBy(F.col("n_name").alias("nation"), F.col("r_name").alias("region")).agg(F.count(F.lit(1)).alias("links"))


@query("q_udtf_tiles", ORACLES["q_tile_load"])
def udtf_tiles(spark, sf_dir):
    from spatial_links.functions.sqlfuncs import tiles_in_sql

    s = L.layer(spark, sf_dir, "lakes")
    return tiles_in_sql(s, grid.mean_tile(s)).groupBy("tx", "ty").agg(F.count(F.lit(1)).alias("n"))


@query("q_sql_functions", O.scored("p7", "mbro") + " select sid, tid, round(weight, 6) as mbro from w")
def sql_functions(spark, sf_dir):
    from spatial_links.functions.sqlfuncs import register_functions

    register_functions(spark)
    _p7(spark, sf_dir)[0].createOrReplaceTempView("sl_pairs")
    box = "s_xmin, s_ymin, s_xmax, s_ymax, t_xmin, t_ymin, t_xmax, t_ymax"
    return spark.sql(f"select sid, tid, round(sl_mbro({box}), 6) as mbro from sl_pairs where sl_boxes_meet({box})")


@query("q_sql_spatial_join", f"{O.pair_ctes('p5')} select sid, tid from flags where touches")
def sql_spatial_join(spark, sf_dir):
    from spatial_links.functions.sqlfuncs import spatial_join_sql

    for name, d in zip(("sl_left", "sl_right"), L.pair(spark, sf_dir, "p5"), strict=True):
        d.createOrReplaceTempView(name)
    return spatial_join_sql(spark, "sl_left", "sl_right", "touches")


# Streams

_VZ = f"with z as ({_ZONES}), v as ({_VISITS}), l as (select z.gid as sid, v.gid as tid, v.ts, v.user_id from z join v on z.x <= v.x + v.w and v.x <= z.x + z.w and z.y <= v.y and v.y <= z.y + z.h)"


def _stream(spark, sf_dir, files: int = 3) -> DataFrame:
    """All events as a stream of files that arrive in the order of their times, one a trigger."""
    from spatial_links.streaming import jobs as J

    path, d = new_path(spark, "events"), L.table(spark, sf_dir, "events")
    at = F.unix_micros(F.col("ts").cast("timestamp"))
    lo, hi = d.agg(F.min(at), F.max(at)).first()
    part = F.floor((at - lo) * files / (hi - lo + 1)) if lo is not None else F.lit(0)
    for k in range(files):
        d.where(part == k).coalesce(1).write.mode("append").parquet(path)
    return J.visit_stream(spark, path, per_trigger=1)


def _ran(stream: DataFrame, mode: str = "append") -> DataFrame:
    from spatial_links.streaming import jobs as J

    return J.run_to_table(stream, new_path(stream.sparkSession, "stream"), mode)


def _stream_links(spark, sf_dir) -> DataFrame:
    from spatial_links.streaming import jobs as J

    return J.related_visits(_stream(spark, sf_dir), L.zones(spark, sf_dir))


@query("q_stream_static", _VZ + " select sid, tid from l")
def stream_static(spark, sf_dir):
    return _ran(_stream_links(spark, sf_dir).select("sid", "tid"))


@query("q_stream_left", _VZ + " select cast(null as bigint) as sid, v.gid as tid from v where v.gid not in (select tid from l) union all select sid, tid from l")
def stream_left(spark, sf_dir):
    from spatial_links.streaming import jobs as J

    out = new_path(spark, "left")
    J.left_batches(_stream(spark, sf_dir), L.zones(spark, sf_dir), out, new_path(spark, "stream")).awaitTermination()
    return spark.read.parquet(out).select("sid", "tid")


@query("q_stream_tumbling", _VZ + " select time_bucket(interval '1 day', ts) as start, count(*) as links from l group by 1")
def stream_tumbling(spark, sf_dir):
    from spatial_links.streaming import jobs as J

    return _ran(J.windowed_counts(_stream_links(spark, sf_dir), "1 day"), "complete").select(F.col("start").cast("timestamp_ntz").alias("start"), "links")


@query("q_stream_sliding", _VZ + ", w as (select unnest(range(0, 4)) as k), s as (select time_bucket(interval '6 hours', ts) - k * interval '6 hours' as start from l, w) select start, count(*) as links from s group by 1")
def stream_sliding(spark, sf_dir):
    from spatial_links.streaming import jobs as J

    return _ran(J.windowed_counts(_stream_links(spark, sf_dir), "1 day", "6 hours"), "complete").select(F.col("start").cast("timestamp_ntz").alias("start"), "links")


@query("q_stream_session", _VZ + ", o as (select user_id, ts, case when lag(ts) over w is null or ts >= lag(ts) over w + interval '30 minutes' then 1 else 0 end as new from l window w as (partition by user_id order by ts)), g as (select user_id, ts, sum(new) over (partition by user_id order by ts) as k from o) select user_id, min(ts) as start, count(*) as links from g group by user_id, k")
def stream_session(spark, sf_dir):
    from spatial_links.streaming import jobs as J

    return _ran(J.session_counts(_stream_links(spark, sf_dir)), "complete").select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "links")


@query("q_stream_dedup", "select gid as tid from (" + _VISITS + ")")
def stream_dedup(spark, sf_dir):
    from spatial_links.streaming import jobs as J

    path = new_path(spark, "events")
    d = L.table(spark, sf_dir, "events")
    d.unionByName(d.where("event_id % 3 = 0")).coalesce(1).write.parquet(path)
    return _ran(J.without_repeats(J.visit_stream(spark, path, 100))).select(F.col("gid").alias("tid"))


@query("q_stream_late", "select count(*) as read, true as late from events")
def stream_late(spark, sf_dir):
    """Events out of order over several triggers: rows later than the watermark are dropped, and their number is known."""
    from spatial_links.streaming import jobs as J

    path, d = new_path(spark, "events"), L.table(spark, sf_dir, "events")
    for k in range(4):
        d.where(F.col("event_id") % 4 == k).coalesce(1).write.mode("append").parquet(path)
    counts = J.visit_stream(spark, path, 1).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n"))
    q = counts.writeStream.format("parquet").option("path", new_path(spark, "late")).outputMode("append").option("checkpointLocation", new_path(spark, "late")).trigger(availableNow=True).start()
    q.awaitTermination()
    late = sum(o["numRowsDroppedByWatermark"] for p in q.recentProgress for o in p["stateOperators"])
    rows = sum(p["numInputRows"] for p in q.recentProgress)
    return spark.range(1).select(F.lit(int(rows)).cast("bigint").alias("read"), F.lit(late > 0).alias("late"))


@query("q_stream_progressive")
def stream_progressive(spark, sf_dir):
    from spatial_links.streaming import jobs as J

    out = new_path(spark, "progressive")
    J.progressive_batches(_stream(spark, sf_dir), L.zones(spark, sf_dir), 0.1, out, new_path(spark, "stream")).awaitTermination()
    return spark.read.parquet(out)


@query("q_stream_state", _VZ + " select sid, count(*) as links from l group by 1")
def stream_state(spark, sf_dir):
    from spatial_links.streaming import jobs as J

    d = _ran(J.running_totals(_stream_links(spark, sf_dir)), "update")
    return d.groupBy("sid").agg(F.max("links").alias("links"))


@query("q_stream_stream", f"with v as ({_VISITS}), a as (select * from v where event_type = 'click'), b as (select * from v where event_type = 'purchase') select a.gid as sid, b.gid as tid from a join b on a.y = b.y and a.x <= b.x + b.w and b.x <= a.x + a.w and b.ts between a.ts - interval '2 hours' and a.ts + interval '2 hours'")
def stream_stream(spark, sf_dir):
    from spatial_links.streaming import jobs as J

    v = _stream(spark, sf_dir)
    return _ran(J.meetings(v.where("event_type = 'click'"), v.where("event_type = 'purchase'"))).select("sid", "tid")


# Catalogue and tuning


@query("q_grid_search")
def grid_search(spark, sf_dir):
    s, t = L.pair(spark, sf_dir, "p1")
    found = M.grid_search(s, t, "two_sided_grid", {"tile_w": [2.0, 8.0], "tile_h": [2.0, 8.0]})
    return spark.createDataFrame([(p["tile_w"], p["tile_h"], v) for p, v in found], "tile_w double, tile_h double, seconds double")


@query("q_grid_search_recall")
def grid_search_recall(spark, sf_dir):
    """The configuration of highest progressive recall at a tenth of the candidates."""
    s, t = L.pair(spark, sf_dir, "p7")
    found = M.grid_search(s, t, "source_grid", {"scheduler": ["global", "geometry", "round_robin"], "weight": ["js", "mbro"]}, "recall")
    return spark.createDataFrame([(p["scheduler"], p["weight"], round(v, 6)) for p, v in found], "scheduler string, weight string, ratio double")


_SHARES_OF = {"streams": "lakes:streams", "parks": "lakes:parks", "lots": "lakes:lots"}


@query("q_recommend", " union all ".join(f"select '{n}' as target, * from ({_with_flags(O.scored(p, 'js', 'mbro'), p)}, rk as (select intersects, row_number() over (order by {_BEST}) as position from w join flags using (sid, tid)) select count(*) filter (where intersects) as found from rk where position <= (select cast(ceil(0.02 * count(*)) as bigint) from w))" for n, p in _SHARES_OF.items()))
def recommend(spark, sf_dir):
    found = M.recommend_targets(L.layer(spark, sf_dir, "lakes"), {n: L.layer(spark, sf_dir, n) for n in _SHARES_OF}, 0.02)
    return spark.createDataFrame(found, "target string, found bigint")


def queries() -> dict[str, Query]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
