"""The experiment workloads, timed: filtering and verification per method, scalability, parallel joins, progressive orders."""

from __future__ import annotations

import time
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spatial_links.operators import grid, measures, schedule, verify, weights
from spatial_links.plans import methods as M
from spatial_links.plans.methods import MethodSpec
from spatial_links.plans.shared import dropped, settled, written
from spatial_links.sources import layers as L

SERIAL = ("two_sided_grid", "source_grid", "plane_sweep_list", "plane_sweep_stripes", "pbsm", "stripe_hash", "stripe_str", "rtree", "quadtree", "crtree")
#: The tuned configurations that the parallel comparison uses.
PARALLEL = {
    "sampled_partition": MethodSpec("sampled_partition_join", {"partitioner": "kdb", "local": "rtree"}),
    "partition_pair_fixed": MethodSpec("partition_pair_join", {"nx": 512, "ny": 512}),
    "partition_pair_str": MethodSpec("partition_pair_join", {"partitioner": "str"}),
    "skew_aware": MethodSpec("skew_aware_join", {"partitioner": "quadtree", "local": "rtree"}),
    "zorder": MethodSpec("zorder_join", {"precision": 20}),
    "distributed_grid": MethodSpec("distributed_grid"),
    "distributed_grid_swapped": MethodSpec("distributed_grid", {"source": "right"}),
    "broadcast": MethodSpec("broadcast_join"),
}


#: Runs of which a reported time is the mean.
REPETITIONS = 5


def seconds(df: DataFrame) -> float:
    at = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - at


def run_report(source: DataFrame, target: DataFrame, spec: MethodSpec, repetitions: int = REPETITIONS) -> dict:
    """Filtering, verification and total seconds (means), candidates and related pairs of a method.

    Candidates are written once, and verification alone is timed from there; the total is a run from layer to matrix.
    """
    t_f = sum(seconds(M.candidate_pairs(source, target, spec).select("sid", "tid")) for _ in range(repetitions)) / repetitions
    pairs = written(M.candidate_pairs(source, target, spec).select("sid", "tid"))
    m = verify.matrices(verify.attach(pairs, source, target))
    t_v = sum(seconds(m) for _ in range(repetitions)) / repetitions
    total = sum(seconds(M.pair_matrices(source, target, spec)) for _ in range(repetitions)) / repetitions
    n, r = m.agg(F.count(F.lit(1)), F.sum(M.related_of(m).cast("long"))).first()
    dropped(pairs)
    return {"method": spec.name, "params": spec.params, "measures": {"filter_seconds": t_f, "verify_seconds": t_v, "total_seconds": total, "candidates": n, "related": r or 0}}


def subset(layer: DataFrame, k: int) -> DataFrame:
    """k tenths of a layer, by blocks of space, so that related pairs grow in proportion."""
    return layer.where(F.expr(f"(x div 10) % 10 < {k}"))


def serial_scalability(spark: SparkSession, sf_dir: str, tenths: tuple[int, ...] = tuple(range(1, 11)), methods: tuple[str, ...] = SERIAL, repetitions: int = REPETITIONS) -> list[dict]:
    """The filters on growing subsets of the first pair; each layer's subset is written first."""
    out = []
    for k in tenths:
        s, t = (written(subset(d, k)) for d in L.pair(spark, sf_dir, "p1"))
        out += [run_report(s, t, MethodSpec(m), repetitions) | {"tenths": k} for m in methods]
        dropped(s)
        dropped(t)
    return out


def serial_comparison(spark: SparkSession, sf_dir: str, pairs: tuple[str, ...] = ("p1", "p2", "p3"), repetitions: int = REPETITIONS) -> list[dict]:
    return [run_report(*L.pair(spark, sf_dir, p), MethodSpec(m), repetitions) | {"pair": p} for p in pairs for m in SERIAL]


def parallel_scalability(spark: SparkSession, sf_dir: str, tenths: tuple[int, ...] = tuple(range(1, 11)), repetitions: int = REPETITIONS) -> list[dict]:
    """The parallel joins on growing subsets of the first pair, with one serial configuration to compare."""
    out = []
    for k in tenths:
        s, t = (written(subset(d, k)) for d in L.pair(spark, sf_dir, "p1"))
        specs = PARALLEL | {"one_task": MethodSpec("plane_sweep_list", {"strips": 1})}
        out += [run_report(s, t, spec, repetitions) | {"tenths": k, "configuration": name} for name, spec in specs.items()]
        dropped(s)
        dropped(t)
    return out


def parallel_comparison(spark: SparkSession, sf_dir: str, pairs: tuple[str, ...] = ("p1", "p2", "p3", "p4", "p5", "p6"), repetitions: int = REPETITIONS) -> list[dict]:
    return [run_report(*L.pair(spark, sf_dir, p), spec, repetitions) | {"pair": p, "configuration": name} for p in pairs for name, spec in PARALLEL.items()]


def memory_limit(source: DataFrame, target: DataFrame, limit: int) -> dict[str, str]:
    """What each serial method does in `limit` bytes: it runs, or needs more than that for what it keeps."""
    r = measures.resident_bytes(source, target).first()
    need = {"frugal": r.frugal, "intensive": r.intensive}
    return {m: "runs" if need[M.method(m).memory] <= limit else f"needs {need[M.method(m).memory]} bytes" for m in SERIAL}


def speed_up(serial: list[dict], parallel: list[dict]) -> dict[str, float]:
    """How much faster each parallel configuration's run is than the best serial one's."""
    best = min(r["measures"]["total_seconds"] for r in serial)
    return {r["configuration"]: best / r["measures"]["total_seconds"] for r in parallel}


#: The orders that are compared, with their weights: an order's own name, or dynamic_ and the static order it starts from.
ORDERS = {"global_js": ("js", None), "global_mbro": ("mbro", None), "composite": ("js", "mbro"), "unordered": ("js", None), "ideal": ("js", None)}
_FROM = {"dynamic_js": "global_js", "dynamic_mbro": "global_mbro", "dynamic_composite": "composite"}
FRACTIONS = tuple(k / 20 for k in range(1, 11))


def progressive_comparison(spark: SparkSession, sf_dir: str, pair: str = "p7", methods: tuple[str, ...] = (*ORDERS, "dynamic_js", "dynamic_mbro", "dynamic_composite"), fractions: tuple[float, ...] = FRACTIONS) -> DataFrame:
    """(method, and the measures of `measures.progressive`) at each budget, a share of all candidates.

    A dynamic order is a run of its own at each budget: it retains the best pairs of that budget and reorders them as
    related pairs are found, so it has the static order's precision and recall, and differs in when pairs are found.
    """
    s, t = L.pair(spark, sf_dir, pair)
    about = tuple(grid.stats(s, t))
    pairs = grid.join_tiles(s, t, about[0].tile(), carry=True, about=about).withColumn("matrix", verify.matrix_of())
    schemes = sorted({w for n in methods for w in ORDERS[_FROM.get(n, n)] if w})
    # One join for all orders: the weights of a pair, and whether it is related.
    every = written(pairs.select("sid", "tid", *(weights.weight(w).alias(w) for w in schemes), M.related_of(pairs).alias("related")))
    total, found = every.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.col("related").cast("long")), F.lit(0))).first()
    budgets = {f: schedule.Budget(fraction=f).pairs(total) for f in fractions}
    most = max(budgets.values())

    def ranked(name: str, keep: tuple[str, ...]) -> DataFrame:
        one, two = ORDERS[name]
        scored = every.select("sid", "tid", F.col(one).alias("weight"), (F.col(two) if two else F.lit(0.0)).alias("second"), "related")
        if name == "ideal":
            return schedule.ideal(scored, None, most, keep)
        return (schedule.unordered if name == "unordered" else schedule.global_top)(scored, most, keep=keep)

    def static(name: str) -> DataFrame:
        top = ranked(name, ("related",))
        out = written(measures.progressive(top, budgets, found))
        dropped(top)
        return out

    def dynamic(name: str) -> DataFrame:
        top = ranked(name, ("sid", "tid", "weight", "second", "related"))
        # The largest budgets are the first shards, so that no long task begins last.
        large = sorted(budgets.values(), reverse=True)
        runs = F.explode(F.array(*(F.struct(F.lit(k).alias("run"), F.lit(b).cast("long").alias("upto")) for k, b in enumerate(large))))
        each = top.select("*", runs.alias("r")).where("position <= r.upto").select(F.col("r.run").alias("run"), "sid", "tid", "weight", "second", "related")
        done = schedule.dynamic_top(each, shard=F.col("run"), shards=len(large)).select("shard", "position", "related")
        last = len(large) - 1
        out = settled(measures.progressive(done, dict(sorted(budgets.items())), found, F.lit(last) - F.col("shard")))
        dropped(top)
        return out

    rows = [(dynamic(_FROM[n]) if n in _FROM else static(n)).select(F.lit(n).alias("method"), "*") for n in methods]
    dropped(every)
    return reduce(DataFrame.unionByName, rows)


def complexity_fit(source: DataFrame, target: DataFrame, capacity: int = 16, shares: tuple[int, ...] = (4, 2, 1)) -> dict[str, list[tuple[int, int, int]]]:
    """Work counters of the tree filters on growing sides: (sources, targets, tree nodes visited), summed over cells.

    Sides grow by a hash of the id. The trees are built and asked in the tasks of the cells.
    """
    import numpy as np
    import pyarrow as pa

    from spatial_links.operators import local_index as I
    from spatial_links.operators import partitioned as P

    sample = P.sampled(source, target)
    cells = P.make_cells("kdb", sample)
    out: dict[str, list[tuple[int, int, int]]] = {}

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        a, b = (np.column_stack([t.column(f"{p}_{c}").to_numpy() for c in P.BOX]).reshape(-1, 4) for t, p in ((left, "s"), (right, "t")))
        trees = {"rtree": I.r_tree(a, capacity), "quadtree": I.QuadTree(a, capacity), "crtree": I.cr_tree(a, capacity)}
        for t in trees.values():
            t.query(b)
        return pa.table({"tree": list(trees), "n": [len(a)] * 3, "m": [len(b)] * 3, "visited": pa.array([int(t.visited) for t in trees.values()], pa.int64())})

    for share in shares:
        some = lambda d: d.where(F.pmod(F.xxhash64("gid"), F.lit(share)) == 0).select("gid", *P.BOX)
        s, t = (P.prefixed(P.dealt(some(d), cells), p, (*P.BOX, "pid")) for d, p in ((source, "s"), (target, "t")))
        each = s.groupBy("s_pid").cogroup(t.groupBy("t_pid")).applyInArrow(run, "tree string, n long, m long, visited long")
        for r in each.groupBy("tree").agg(F.sum("n").alias("n"), F.sum("m").alias("m"), F.sum("visited").alias("v")).collect():
            out.setdefault(r.tree, []).append((r.n, r.m, r.v))
    return out
