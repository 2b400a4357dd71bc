"""Methods by name: validated parameters, candidate pairs, links; the registry that documents and extends them."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spatial_links.operators import grid, local_index, partitioned, verify
from spatial_links.operators.grid import Stats, Tile


@dataclass(frozen=True)
class Param:
    name: str
    kind: str
    default: object
    least: float | None = None
    most: float | None = None
    options: tuple = ()
    about: str = ""

    def check(self, value):
        if value is None:
            return value
        if self.options and value not in self.options:
            raise ValueError(f"{self.name}={value!r}: one of {self.options}")
        if self.least is not None and value < self.least or self.most is not None and value > self.most:
            raise ValueError(f"{self.name}={value!r}: {self.least} to {self.most}")
        return value


@dataclass(frozen=True)
class Method:
    """A registered method: run(source, target, params) -> pairs (sid, tid, ...); carries: the pairs hold the geometries."""

    name: str
    about: str
    tiling: str
    execution: str
    memory: str
    evidence: bool
    run: Callable[[DataFrame, DataFrame, dict], DataFrame]
    params: tuple[Param, ...] = ()
    carries: bool = False


@dataclass(frozen=True)
class MethodSpec:
    name: str
    params: dict = field(default_factory=dict)

    def __post_init__(self):
        known = {p.name: p for p in method(self.name).params}
        for k, v in self.params.items():
            if k not in known:
                raise ValueError(f"{self.name} has no parameter {k}; it has {sorted(known)}")
            known[k].check(v)

    def values(self) -> dict:
        return {p.name: self.params.get(p.name, p.default) for p in method(self.name).params}


REGISTRY: dict[str, Method] = {}


def register_method(m: Method) -> Method:
    """Adds a method; any callable from (source, target, params) to pairs joins the registry."""
    REGISTRY[m.name] = m
    return m


def method(name: str) -> Method:
    if name not in REGISTRY:
        raise ValueError(f"no method {name}; there are {sorted(REGISTRY)}")
    return REGISTRY[name]


_TILE = (Param("tile_w", "double", None, 1e-12, None, about="tile width; none: from the data"), Param("tile_h", "double", None, 1e-12, None, about="tile height; none: from the data"))
_NODE = Param("capacity", "int", 16, 2, 256, about="entries of a tree node")
_SAMPLE = (Param("cell_share", "double", None, 1e-5, 1, about="share of the sample that a cell may hold; none: from the rows of both sides"), Param("overflow", "string", "extend", options=("extend", "bucket"), about="outer cells reach to infinity, or one partition takes what lies outside"))
_BUILD = Param("build", "string", "packed", options=("packed", "inserted"), about="how the R-tree is built: packed bottom-up, or box by box with splits")
_STRIPS = Param("strips", "int", None, 1, 1_000_000, about="strips joined in parallel; 1: one task; none: from the rows of both sides")


def _tile(p: dict, *sides: Stats) -> Tile:
    if p.get("tile_w") and p.get("tile_h"):
        return Tile(p["tile_w"], p["tile_h"])
    return grid.joint(*sides).tile()


def smaller(a: Stats, b: Stats) -> bool:
    """Whether the second side has fewer rows, and so is the one to index or to size tiles by."""
    return b.rows < a.rows


def _two_sided(s, t, p):
    about = tuple(grid.stats(s, t))
    tile = _tile(p, *about)
    if p["dedup"] == "refpoint":
        return grid.join_tiles(s, t, tile, carry=p["carry"], about=about)
    if p["swap"] and about[1].area < about[0].area:
        return grid.without_repeats(grid.join_tiles(t, s, tile, own=False), p["dedup"]).select(F.col("tid").alias("sid"), F.col("sid").alias("tid"))
    return grid.without_repeats(grid.join_tiles(s, t, tile, own=False), p["dedup"])


def _source_grid(s, t, p):
    about = tuple(grid.stats(s, t))
    own = about[1] if p["source"] == "smaller" and smaller(*about) else about[0]
    tile = _tile(p, own)
    build = "broadcast" if p["broadcast_rows"] and about[0].rows <= p["broadcast_rows"] and not grid.top_level(tile, *about) else "auto"
    return grid.join_tiles(s, t, tile, carry=p["carry"], build=build, about=about if p["guard"] else None)


def _distributed(s, t, p):
    about = tuple(grid.stats(s, t))
    swap = p["source"] == "right" or p["source"] == "smaller" and smaller(*about)
    return grid.join_tiles(s, t, _tile(p, about[1] if swap else about[0]), carry=p["carry"], about=about, hot_rows=p["hot_rows"])


def _turned(join, s, t, sample, wanted: bool):
    """join(source, target), with the smaller side as source where that is wanted."""
    if wanted and smaller(sample.source, sample.target):
        from dataclasses import replace

        return join(t, s, replace(sample, source=sample.target, target=sample.source)).select(F.col("tid").alias("sid"), F.col("sid").alias("tid"))
    return join(s, t, sample)


def _cell_join(s, t, p, make, local, indexed: bool = False):
    """Cells by make(sample), then `local` in each; an index is built of the smaller side."""
    sample = partitioned.sampled(s, t)
    tile = (lambda d: (d.w, d.h))(sample.source.tile()) if local == "grid" else None
    join = lambda a, b, about: partitioned.join_cells(a, b, make(sample), local, p.get("capacity", 16), tile, about, p.get("block_rows") or partitioned.BLOCK_ROWS)
    return _turned(join, s, t, sample, indexed)


def _strips_of(p):
    return lambda sample: partitioned.strips(sample.points, p["strips"] or sample.cells())


def _sweep(kind):
    return lambda s, t, p: _cell_join(s, t, p, _strips_of(p), kind)


def _sampled_cells(p):
    return lambda sample: partitioned.make_cells(p["partitioner"], sample, p["cell_share"], p["overflow"])


def _fixed(p):
    """nx and ny as given, or as many as the rows of both sides ask for."""
    def make(sample):
        n = max(1, round(sample.cells() ** 0.5))
        return partitioned.fixed_cells(sample.extent(), p.get("nx") or n, p.get("ny") or n)

    return make


def _packed(p, kind: str) -> str:
    return "rtree_inserted" if kind == "rtree" and p.get("build") == "inserted" else kind


def _tree(kind):
    def run(s, t, p):
        build = {
            "rtree": lambda b: (local_index.r_tree if p["build"] == "inserted" else local_index.str_tree)(b, p["capacity"]),
            "quadtree": lambda b: local_index.QuadTree(b, p["capacity"], p.get("max_depth", 16)),
            "crtree": lambda b: local_index.cr_tree(b, p["capacity"], p.get("bits", 8)),
        }[kind]
        a, b = grid.stats(s, t)
        if smaller(a, b):
            return partitioned.broadcast_index(t, s, build, p["limit"]).select(F.col("tid").alias("sid"), F.col("sid").alias("tid"))
        return partitioned.broadcast_index(s, t, build, p["limit"])

    return run


def _broadcast_join(s, t, p):
    build = lambda b: (local_index.r_tree if p["build"] == "inserted" else local_index.str_tree)(b, p["capacity"])
    return partitioned.broadcast_index(s, t, build, p["limit"])


def _skew_aware(s, t, p):
    def make(sample):
        n = max(4, round(sample.cells() ** 0.5))
        cells = partitioned.fixed_cells(sample.extent(), n, n) if p["partitioner"] == "grid" else partitioned.make_cells(p["partitioner"], sample, p["cell_share"], p["overflow"])
        return partitioned.rebalanced(sample, cells, p["skew"])

    return _cell_join(s, t, p, make, _packed(p, p["local"]))


def _partition_pairs(s, t, p):
    """A fixed grid is plain arithmetic, so its cells are tiles of a grid join; sampled cells are dealt by a lookup."""
    if p["partitioner"] != "fixed":
        return _cell_join(s, t, p, _sampled_cells(p), "nested")
    about = tuple(grid.stats(s, t))
    x1, y1, x2, y2 = grid.joint(*about).extent or (0.0, 0.0, 1.0, 1.0)
    return grid.join_tiles(s, t, Tile((x2 - x1 or 1.0) / p["nx"], (y2 - y1 or 1.0) / p["ny"]), about=about)


_CARRY = Param("carry", "boolean", False, about="carry both geometries through the join")
_SIDE = Param("source", "string", "smaller", options=("smaller", "left", "right"), about="the side whose mean sizes the tile")
_LIMIT = Param("limit", "long", partitioned.BROADCAST_BYTES, 0, partitioned.BROADCAST_BYTES, about="bytes of the source boxes and their index")
_BLOCK = Param("block_rows", "int", None, 1, None, about="rows of a side that one task of a full cell holds; none: the default")
_LOCAL = ("nested", "rtree", "quadtree", "grid")
for _m in (
    Method("two_sided_grid", "tiles of the mean size over both sides, or as given; both sides dealt to tiles", "grid", "both", "intensive", True, _two_sided, (*_TILE, Param("dedup", "string", "refpoint", options=("refpoint", "distinct", "group_by", "drop_duplicates", "reduce_by_key"), about="how repeats are kept out"), Param("swap", "boolean", False, about="take the side of the smaller volume as source"), _CARRY), True),
    Method("source_grid", "tiles of the mean source size, or as given; only the source is indexed", "grid", "both", "frugal", True, _source_grid, (*_TILE, Param("source", "string", "left", options=("smaller", "left"), about="the side whose mean sizes the tile"), Param("guard", "boolean", True, about="deal geometries that would lie in too many tiles to coarser ones, and split hot tiles"), Param("broadcast_rows", "int", 0, 0, 5_000_000, about="broadcast sources of at most so many rows"), _CARRY), True),
    Method("plane_sweep_list", "sweep along x with one list per side, in strips of equal load", "partition", "both", "intensive", False, _sweep("list"), (_STRIPS, _BLOCK)),
    Method("plane_sweep_stripes", "sweep along x with lists per stripe", "partition", "both", "intensive", False, _sweep("stripes"), (_STRIPS, _BLOCK)),
    Method("plane_sweep_stops", "the stops of a sweep as two equi-joins on strips, without Python", "partition", "parallel", "frugal", False, lambda s, t, p: partitioned.sweep_pairs(s, t, p["width"]), (Param("width", "double", None, 1e-12, None, about="strip width; none: four mean widths"),)),
    Method("pbsm", "orthogonal partitions, plane sweep within", "partition", "both", "intensive", False, lambda s, t, p: _cell_join(s, t, p, _fixed(p), p["structure"]), (Param("nx", "int", None, 1, 4096, about="partitions along x; none: from the rows"), Param("ny", "int", None, 1, 4096, about="partitions along y; none: from the rows"), Param("structure", "string", "list", options=("list", "stripes"), about="sweep structure"), _BLOCK)),
    Method("stripe_hash", "vertical stripes of the mean source width, an equi-join on stripes", "partition", "both", "frugal", False, lambda s, t, p: partitioned.stripe_pairs(s, t, p["width"]), (Param("width", "double", None, 1e-12, None, about="stripe width; none: mean source width"),)),
    Method("stripe_str", "vertical strips with a packed tree of the sources in each", "partition", "both", "frugal", False, lambda s, t, p: _cell_join(s, t, p, _strips_of(p), "str", True), (_STRIPS, _NODE, _BLOCK)),
    Method("rtree", "an R-tree of the smaller side, sent to all tasks", "tree", "both", "frugal", False, _tree("rtree"), (_NODE, _BUILD, _LIMIT)),
    Method("quadtree", "a quadtree of the smaller side, sent to all tasks", "tree", "both", "frugal", False, _tree("quadtree"), (_NODE, Param("max_depth", "int", 16, 1, 24, about="deepest level"), _LIMIT)),
    Method("crtree", "a packed R-tree with boxes quantised relative to their parent", "tree", "both", "frugal", False, _tree("crtree"), (_NODE, Param("bits", "int", 8, 4, 16, about="bits of a quantised coordinate"), _LIMIT)),
    Method("sampled_partition_join", "cells from a sample, equal partitions joined, nested loop or local index", "tree", "parallel", "intensive", False, lambda s, t, p: _cell_join(s, t, p, _sampled_cells(p), _packed(p, p["local"])), (Param("partitioner", "string", "kdb", options=("kdb", "quadtree"), about="cells"), Param("local", "string", "rtree", options=_LOCAL, about="local join"), *_SAMPLE, _NODE, _BUILD, _BLOCK)),
    Method("broadcast_join", "an R-tree of a source of limited size, targets split, no global join", "tree", "parallel", "frugal", False, _broadcast_join, (_LIMIT, _NODE, _BUILD)),
    Method("partition_pair_join", "user grid, or cells from binary or sort-tile splits of a sample; overlapping partitions joined", "partition", "parallel", "intensive", False, _partition_pairs, (Param("partitioner", "string", "fixed", options=("fixed", "bsp", "str"), about="cells"), Param("nx", "int", 512, 1, 4096, about="columns of a fixed grid"), Param("ny", "int", 512, 1, 4096, about="rows of a fixed grid"), *_SAMPLE, _BLOCK)),
    Method("distributed_grid", "tiles of the mean source size deal both sides; one equi-join", "grid", "parallel", "intensive", True, _distributed, (*_TILE, _SIDE, Param("hot_rows", "int", None, 1, None, about="targets of a tile beyond which it is split; none: from the rows"), _CARRY), True),
    Method("skew_aware_join", "cells are split while they hold a multiple of the smallest; local index on the source", "tree", "parallel", "intensive", False, _skew_aware, (Param("partitioner", "string", "quadtree", options=("grid", "rtree", "quadtree"), about="cells"), Param("local", "string", "rtree", options=("rtree", "quadtree", "grid"), about="local index"), Param("skew", "double", 2.0, 1.1, 100, about="multiple of the smallest cell that is split"), *_SAMPLE, _NODE, _BUILD, _BLOCK)),
    Method("zorder_join", "2^precision tiles on a Z-order curve, equi-join on the curve", "grid", "parallel", "intensive", False, lambda s, t, p: grid.zorder_pairs(s, t, p["precision"], p["carry"]), (Param("precision", "int", 20, 2, 40, about="bits of the curve"), _CARRY), True),
    Method("brute_force", "every pair", "none", "both", "intensive", False, lambda s, t, p: partitioned.brute_pairs(s, t), ()),
):
    register_method(_m)


def candidate_pairs(source: DataFrame, target: DataFrame, spec: MethodSpec | str = "distributed_grid", carry: bool = False) -> DataFrame:
    """Pairs whose closed boxes meet, each once, as the method finds them."""
    spec = MethodSpec(spec) if isinstance(spec, str) else spec
    values = spec.values()
    if carry and method(spec.name).carries:
        values["carry"] = True
    return method(spec.name).run(source, target, values)


def pair_matrices(source: DataFrame, target: DataFrame, spec: MethodSpec | str = "distributed_grid") -> DataFrame:
    """(sid, tid, s_dim, t_dim, matrix) of all candidates; geometries ride through the join or are attached after it."""
    spec = MethodSpec(spec) if isinstance(spec, str) else spec
    pairs = candidate_pairs(source, target, spec, carry=True)
    if "s_xs" not in pairs.columns:
        pairs = verify.attach(pairs.select("sid", "tid"), source, target)
    return verify.matrices(pairs).select("sid", "tid", "s_dim", "t_dim", "matrix")


def discover_links(source: DataFrame, target: DataFrame, spec: MethodSpec | str = "distributed_grid", relations: tuple[str, ...] | None = None, emit: str = "links") -> DataFrame:
    """Links (sid, relation, tid), matrices, or candidate pairs of two layers."""
    if emit == "pairs":
        return candidate_pairs(source, target, spec).select("sid", "tid")
    m = pair_matrices(source, target, spec)
    return m if emit == "matrix" else verify.links(m, relations or verify.RELATIONS)


def make_pipeline(tiling: str, budget: str = "batch", execution: str = "parallel", **params) -> MethodSpec:
    """The default method of a point in the space of tiling, budget and execution."""
    table = {
        ("grid", "parallel"): "distributed_grid", ("tree", "parallel"): "skew_aware_join", ("partition", "parallel"): "partition_pair_join",
        ("grid", "serial"): "source_grid", ("tree", "serial"): "rtree", ("partition", "serial"): "stripe_hash",
    }
    if budget == "progressive" and tiling != "grid":
        raise ValueError("progressive methods need the evidence of a grid")
    if (tiling, execution) not in table:
        raise ValueError(f"no method for {tiling}, {execution}")
    return MethodSpec(table[tiling, execution], params)


def methods_catalog(spark: SparkSession) -> DataFrame:
    """Documentation of every method and parameter: one row per parameter (or one for a method without any)."""
    rows = []
    for m in REGISTRY.values():
        for p in m.params or (None,):
            rows.append((m.name, m.about, m.tiling, m.execution, m.memory, m.evidence, *((p.name, p.kind, str(p.default), p.least, p.most, ",".join(map(str, p.options)), p.about) if p else (None,) * 7)))
    rows = [tuple(float(v) if i in (9, 10) and v is not None else v for i, v in enumerate(r)) for r in rows]
    return spark.createDataFrame(rows, "method string, about string, tiling string, execution string, memory string, evidence boolean, param string, kind string, `default` string, least double, most double, options string, param_about string")


def related_of(matrices: DataFrame):
    """Whether a pair satisfies any positive relation."""
    return verify.relation("intersects", F.col("matrix"), F.col("s_dim"), F.col("t_dim"))


def grid_search(source: DataFrame, target: DataFrame, name: str, space: dict[str, list], objective: str = "seconds", budget: float = 0.1) -> list[tuple[dict, float]]:
    """Every combination of values with its objective, best first.

    objective 'seconds': the time to find all candidates, least first. 'recall': progressive recall (the area under the
    curve against that of an ideal order) of the best `budget` of a grid's candidates, most first; beside the method's
    parameters `space` may then vary scheduler, weight and second.
    """
    import itertools
    import time

    from spatial_links.operators import measures, schedule, weights
    from spatial_links.plans.shared import dropped, written

    def seconds(params: dict) -> float:
        at = time.perf_counter()
        candidate_pairs(source, target, MethodSpec(name, params)).write.format("noop").mode("overwrite").save()
        return time.perf_counter() - at

    flags, joined = None, {}
    schemes = sorted({w for k, default in (("weight", ["js"]), ("second", [])) for w in space.get(k, default) if w})
    if objective == "recall":
        m = pair_matrices(source, target)
        flags = written(m.select("sid", "tid", related_of(m).alias("related")))
        total, found = flags.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.col("related").cast("long")), F.lit(0))).first()
        limit = schedule.Budget(fraction=budget).pairs(total)

    def recall(params: dict) -> float:
        own = dict(params)
        order, one, two = own.pop("scheduler", "global"), own.pop("weight", "js"), own.pop("second", None)
        if repr(own) not in joined:  # one join for all orders of the same candidates
            pairs = candidate_pairs(source, target, MethodSpec(name, own))
            joined[repr(own)] = written(pairs.select("sid", "tid", "tx", "ty", *(weights.weight(w).alias(w) for w in schemes)))
        scored = joined[repr(own)].select("sid", "tid", F.col(one).alias("weight"), (F.col(two) if two else F.lit(0.0)).alias("second"), "tx", "ty")
        top = schedule.scheduler(order)(scored, limit)
        out = measures.progressive(top.join(flags, ["sid", "tid"]).select("position", "related"), {budget: limit}, found).first().ratio
        if not {*top.inputFiles()} & {*scored.inputFiles()}:  # a scheduler may have answered from the candidates' own table
            dropped(top)
        return out

    measure = {"seconds": seconds, "recall": recall}[objective]
    out = []
    for values in itertools.product(*space.values()):
        params = dict(zip(space, values, strict=True))
        out.append((params, measure(params)))
    for d in (*joined.values(), *([flags] if flags is not None else [])):
        dropped(d)
    return sorted(out, key=lambda x: x[1] if objective == "seconds" else -x[1])


def recommend_targets(source: DataFrame, targets: dict[str, DataFrame], budget: float = 0.02) -> list[tuple[str, int]]:
    """Targets by how many related pairs a small share of their best candidates holds."""
    from spatial_links.operators.schedule import Budget, global_top
    from spatial_links.operators.weights import scored
    from spatial_links.plans.shared import dropped, written

    out = []
    for name, t in targets.items():
        best = written(scored(candidate_pairs(source, t, MethodSpec("source_grid")), "js", "mbro"))
        top = global_top(best, Budget(fraction=budget).pairs(best.count()))
        m = verify.matrices(verify.attach(top.select("sid", "tid"), source, t))
        out.append((name, m.where(related_of(m)).count()))
        dropped(best)
    return sorted(out, key=lambda x: (-x[1], x[0]))
