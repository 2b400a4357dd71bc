"""Named queries against their SQL on the smallest tables, identities of relations, readers and cleaning."""

import pytest

import __spark_entry__ as entry
from spatial_links.functions import geometry as G
from spatial_links.plans import queries as Q
from spatial_links.sources import layers as L
from spatial_links.sources import readers as R

from .conftest import DATA, same

CHOSEN = (
    "q_layer_lakes", "q_layer_mixed", "q_layer_routes", "q_geom_measures", "q_tile_load", "q_cand_two_grid", "q_cand_undeduped", "q_links_p3", "q_links_p4", "q_links_p5", "q_links_p6", "q_matrix_p1", "q_rel_touches",
    "q_relation_counts", "q_relation_identity", "q_relation_rollup", "q_w_chi2", "q_w_composite", "q_sched_geometry_both", "q_sched_roundrobin_both", "q_sched_tiles_desc", "q_sched_sharded", "q_sched_sharded_round_robin", "q_sched_time_budget", "q_eval_budgets_p2", "q_cand_bloom", "q_cand_sweep_window", "q_clean_report", "q_stream_left", "q_disjoint_counts", "q_recommend", "q_geojson_roundtrip",
    "q_ntriples_roundtrip", "q_jsonrdf_read", "q_sparql_read", "q_tsv_read", "q_udtf_tiles", "q_sql_functions", "q_stream_static", "q_stream_session", "q_stream_stream", "q_self_join", "q_attr_join_nation",
)


@pytest.mark.parametrize("name", CHOSEN)
def test_query_equals_its_sql(spark, duck, name):
    assert same(spark, duck, Q.QUERIES[name], Q.ORACLES[name]) is not None


def test_contract(spark):
    found = entry.queries()
    assert set(entry.oracle_sql()) <= set(found)
    assert entry.entry(spark).count() == 9


def test_cleaning_gives_reasons(spark, tmp_path):
    lines = ["LINESTRING (0 0, 1 1)", "LINESTRING (0 0, 0 0, 2 2)", "POLYGON ((0 0, 4 0, 4 4, 0 4, 0 0), (1 1, 2 1, 2 2, 1 2, 1 1))", "POLYGON ((0 0, 0 4, 4 4, 4 0, 0 0))", "POINT (1 2)", "LINESTRING (0 0)", "LINESTRING (3 3, 3 3)", "POLYGON ((0 0, 1 0, 1 1))", "POLYGON ((0 0, 1 1, 2 2, 0 0))", "LINESTRING (a b, c d)", "hello", "", "LINESTRING (0 0, NaN 1)"]
    path = str(tmp_path / "w")
    spark.createDataFrame([(x,) for x in lines], "value string").coalesce(1).write.text(path)
    good, bad = R.clean(R.read_wkt(spark, path))
    assert sorted(r.npoints for r in good.collect()) == [2, 2, 5, 10]
    shell = good.where("npoints = 5").first()
    assert shell.xs[1] == 4.0 and shell.ys[1] == 0.0  # turned against the clock
    reasons = {}
    for r in bad.collect():
        reasons.setdefault(r.reason, set()).add(r.line)
    assert reasons["unsupported_type"] == {"POINT (1 2)"}
    assert reasons["too_few_points"] == {"LINESTRING (0 0)", "LINESTRING (3 3, 3 3)"}
    assert reasons["open_ring"] == {"POLYGON ((0 0, 1 0, 1 1))"} and reasons["flat_ring"] == {"POLYGON ((0 0, 1 1, 2 2, 0 0))"}
    assert "hello" in reasons["parse_error"] and "LINESTRING (a b, c d)" in reasons["bad_number"]


def test_links_are_written_and_read(spark, tmp_path):
    from spatial_links.plans import methods as M

    s, t = L.pair(spark, DATA, "p5")
    links = M.discover_links(s, t)
    R.write_links(links, str(tmp_path / "p"))
    back = spark.read.parquet(str(tmp_path / "p"))
    assert back.count() == links.count() and back.where("relation = 'equals'").count() == links.where("relation = 'equals'").count()
    named = links.join(s.select(s.gid.alias("sid"), s.uri.alias("suri")), "sid").join(t.select(t.gid.alias("tid"), t.uri.alias("turi")), "tid")
    R.write_links(named, str(tmp_path / "n"), "ntriples")
    assert spark.read.text(str(tmp_path / "n")).count() == links.count()


def test_range_filter_reaches_the_files(spark, tmp_path):
    L.layer(spark, DATA, "parks").write.parquet(str(tmp_path / "l"))
    d = R.read_layer(spark, str(tmp_path / "l")).where(G.in_window(1, 1, 5, 5)).select("gid")
    text = d._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(xmin)" in text and "xs" not in text.split("ReadSchema")[1]


def test_runs_are_compared(spark, tmp_path):
    for v in (1.0, 3.0):
        R.append_run(spark, str(tmp_path / "r"), {"method": "pbsm", "params": {"nx": 4}, "measures": {"filter_seconds": v}})
    r = R.compare_runs(spark, str(tmp_path / "r")).first()
    assert (r.method, r.measure, r.runs, r["mean"]) == ("pbsm", "filter_seconds", 2, 2.0)


def test_slanting_lines_against_the_kernel(spark):
    """The skewed workload's relation counts are those of all pairs of boxes that meet, verified one by one."""
    from spatial_links.operators import verify

    s, t = L.layer(spark, DATA, "lakes").where("gid % 7 = 0"), L.layer(spark, DATA, "walks").where("gid % 7 = 0")
    from spatial_links.operators import partitioned
    from spatial_links.plans import methods as M

    want = verify.links(verify.matrices(verify.attach(partitioned.brute_pairs(s, t), s, t)))
    got = M.discover_links(s, t, M.MethodSpec("skew_aware_join", {"partitioner": "rtree"}))
    assert got.exceptAll(want).count() == want.exceptAll(got).count() == 0 < got.count()


def test_sparql_reads_a_given_table(spark, duck):
    """The endpoint query asks for rows of a table (before: squares made up in the fetcher); pages are read as they were."""
    assert len(same(spark, duck, Q.QUERIES["q_sparql_read"], Q.ORACLES["q_sparql_read"])) == L.layer(spark, DATA, "lakes").count() > 0
    good, _ = R.clean(R.read_endpoint(spark, "SELECT ?s ?wkt", "spatial_links.sources.local_endpoint:fetch", pages=3, page_size=100))
    assert good.count() == 250


def test_catalog_is_no_query():
    """It reads no table; the registry's documentation stays in `methods_catalog` and on the command line."""
    assert "q_catalog" not in entry.queries()


def test_ratio_keeps_no_shuffle(spark, monkeypatch):
    """Each pair's counts are settled before the next pair begins: the result's plan has no exchange (before: all pairs in one)."""
    monkeypatch.setattr(L, "PAIRS", {"p5": L.PAIRS["p5"], "p2": L.PAIRS["p2"]})
    d = Q.QUERIES["q_qualifying_ratio"](spark, DATA)
    assert "Exchange" not in d._jdf.queryExecution().executedPlan().toString()
    assert {r.pair: 0 < r.related <= r.candidates for r in d.collect()} == {"p5": True, "p2": True}


def test_one_join_for_all_orders(spark, monkeypatch):
    from spatial_links.plans import experiments as E
    from spatial_links.plans import methods as M

    calls = []
    for module, name in ((E.grid, "join_tiles"), (M, "candidate_pairs"), (M, "pair_matrices")):
        monkeypatch.setattr(module, name, lambda *a, f=getattr(module, name), n=name, **k: (calls.append(n), f(*a, **k))[1])
    got = E.progressive_comparison(spark, DATA, "p9", ("global_js", "composite", "ideal"), (0.1,)).collect()
    assert len(got) == 3 and calls == ["join_tiles"]  # before: one more for each order, and one for the matrices
    calls.clear()
    s, t = L.pair(spark, DATA, "p9")
    found = M.grid_search(s, t, "source_grid", {"scheduler": ["global", "unordered"], "weight": ["js", "mbro"]}, "recall")
    assert len(found) == 4 and found[0][1] >= found[-1][1] > 0
    assert calls.count("candidate_pairs") == 2  # the matrices' and the search's; before: one for each combination


def test_boxes_settle_stream_pairs(spark):
    """Rectangles and axis-parallel segments need no matrix (before: all pairs went to Python); others are verified."""
    from spatial_links.streaming import jobs as J

    line = lambda x1, y1, x2, y2: ("L", 1, [x1, x2], [y1, y2], [2])
    rect = ("P", 2, [0.0, 4.0, 4.0, 0.0, 0.0], [0.0, 0.0, 4.0, 4.0, 0.0], [5])
    elbow = ("P", 2, [0.0, 4.0, 4.0, 3.0, 3.0, 0.0, 0.0], [0.0, 0.0, 1.0, 1.0, 4.0, 4.0, 0.0], [7])
    kite = ("P", 2, [0.0, 2.0, 4.0, 2.0, 0.0], [2.0, 0.0, 2.0, 4.0, 2.0], [5])
    layer = lambda rows: G.with_mbr(spark.createDataFrame([(i, *r) for i, r in enumerate(rows)], "gid long, geom_type string, dim int, xs array<double>, ys array<double>, ring_ends array<int>"))
    zones = layer([rect, elbow, kite])
    visits = layer([line(3.5, 3.0, 6.0, 3.0), line(3.5, 9.0, 9.0, 3.5), line(-1.0, 1.0, 1.0, -1.0), line(4.0, 0.0, 4.0, 9.0), line(3.9, 4.5, 4.5, 3.9), line(5.0, 0.0, 6.0, 0.0)])
    visits = visits.selectExpr("*", "timestamp '2024-01-01' as ts", "1L as user_id", "'view' as event_type")
    want = {(r.sid, r.tid) for r in J.related(J.stream_links(visits, zones)).collect()}
    d = J.related_visits(visits, zones)
    got = [(r.sid, r.tid) for r in d.collect()]
    assert len(got) == len(set(got)) and set(got) == want and {(0, 0), (0, 3)} <= want and (1, 0) not in want
    plain = J.related_visits(visits, zones.where("gid = 0"))._jdf.queryExecution().optimizedPlan().toString()
    assert plain.count("ArrowEvalPython") == 1  # of slanting visits only
