"""Shared pieces of the text operators: reading tables, written intermediate tables, connected components."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spatial_links.plans.shared import dropped, new_path


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def materialise(df: DataFrame, name: str, files: int | None = None) -> DataFrame:
    """Writes df to the shared folder and reads it back: lineage is cut and a lost executor costs no recomputation.

    files: at most so many, for tables that are much smaller than what they are made of.
    """
    spark = df.sparkSession
    path = new_path(spark, name)
    (df.coalesce(files) if files else df).write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


#: Rows of ids that may be broadcast: a fixed bound, checked by a count.
BROADCAST_IDS = 1_000_000


def by_ids(rows: DataFrame, ids: DataFrame, keys: list[str], how: str) -> DataFrame:
    """Joins written, distinct ids to rows: broadcast below a checked count, else shuffled."""
    return rows.join(F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids, keys, how)


#: Rows of a key beyond which it is joined by broadcast, and the share of all rows that decides it for large inputs.
HOT_ROWS, HOT_SHARE = 2_000, 1e-5


def join_hot(left: DataFrame, right: DataFrame, keys: str | list[str], how: str = "inner", counted: DataFrame | None = None, sizes: DataFrame | None = None) -> DataFrame:
    """left join right on keys that are distinct in right, without a task for all rows of a frequent key.

    The rows of frequent keys meet right's rows of these keys by broadcast: there are at most 1 / HOT_SHARE of them,
    whatever the input. counted: where to count keys, if not in left. sizes: counts that are known, (keys, rows).
    """
    keys = [keys] if isinstance(keys, str) else keys
    n = sizes.select(*keys, "rows") if sizes is not None else (left if counted is None else counted).groupBy(*keys).agg(F.count(F.lit(1)).alias("rows"))
    n = n.where(F.col("rows") > HOT_ROWS)
    total = n.agg(F.sum("rows")).first()[0]
    if total is None:
        return left.join(right, keys, how)
    hot = materialise(n.where(F.col("rows") > int(total * HOT_SHARE)).select(*keys), "hot", 1)
    often = materialise(right.join(F.broadcast(hot), keys, "left_semi"), "often", 1)
    cold = left.join(F.broadcast(hot), keys, "left_anti").join(right, keys, how)
    return left.join(F.broadcast(hot), keys, "left_semi").join(F.broadcast(often), keys, how).unionByName(cold)


def drop(df: DataFrame) -> None:
    """Deletes the files of a table that `materialise` wrote, once nothing reads it any more."""
    dropped(df)


def small(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    """A short list of rows as a plan of literals, so that no Python worker is needed to make it."""
    kinds = [f.split() for f in schema.split(", ")]
    if not rows:
        return spark.range(0).select(*(F.lit(None).cast(t).alias(c) for c, t in kinds))
    each = [F.struct(*(F.lit(v).cast(t).alias(c) for v, (c, t) in zip(r, kinds, strict=True))) for r in rows]
    return spark.range(1).select(F.inline(F.array(*each)))


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def connected_components(edges: DataFrame, files: int | None = None, max_rounds: int = 60) -> DataFrame:
    """Components of an undirected graph by alternating large-star and small-star.

    edges: (u long, v long), in any direction, repeats allowed. Returns (node, component) with
    component the smallest node of the component, for every node of an edge with u != v.
    The minimum of a neighbourhood is a partial aggregate, and it is joined back to the edges, so a
    node with very many neighbours is never gathered in one place. Each round is a written table.
    """

    def settled(df: DataFrame):
        return df.agg(F.count(F.lit(1)), F.expr("bit_xor(xxhash64(u, v))"), F.sum(F.expr("v % 1000003"))).first()

    cur = materialise(
        edges.where("u is not null and v is not null and u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges", files
    )
    seen = settled(cur)
    for _ in range(max_rounds):
        both = cur.unionByName(cur.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(low, "u").where("v > u and v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        near = large.join(low, "u")
        small = near.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(near.select("u", F.col("m").alias("v"))).distinct()
        nxt = materialise(small, "edges", files)
        drop(cur)
        cur, last, seen = nxt, seen, settled(nxt)
        if last == seen:
            break
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return cur.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(cur.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
