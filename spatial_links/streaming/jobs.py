"""Streaming jobs: targets that arrive as events are joined with static source layers by the same tiles."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spatial_links.functions.geometry import BOX, boxes_meet, prefixed
from spatial_links.operators import grid, verify
from spatial_links.plans.shared import dropped, written
from spatial_links.sources.layers import as_visits

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def visit_stream(spark: SparkSession, path: str, per_trigger: int = 1) -> DataFrame:
    """events files as a stream of visits. The folder is watched; each trigger takes some of its files."""
    schema = spark.read.parquet(path).schema
    return as_visits(spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(path))


VISIT = ("ts", "user_id", "event_type")


def _against(visits: DataFrame, zones: DataFrame, cols: tuple[str, ...] | None = None) -> DataFrame:
    """Pairs of visits (a stream or a batch) and static zones whose boxes meet, each once, with both geometries (or cols)."""
    tile = grid.guarded(grid.mean_tile(zones), zones)
    cols = cols or grid.columns(True)
    s = grid.dealt(grid.ranged(prefixed(zones, "s", cols), tile, "s"), "s")
    t = prefixed(visits, "t", (*cols, *VISIT)).withColumnsRenamed({f"t_{c}": c for c in VISIT})
    t = grid.dealt(grid.ranged(t, tile, "t"), "t").withColumnsRenamed({"tx": "ux", "ty": "uy"})
    return t.join(s, (F.col("tx") == F.col("ux")) & (F.col("ty") == F.col("uy")) & boxes_meet() & grid.owns_pair())


def stream_links(visits: DataFrame, zones: DataFrame) -> DataFrame:
    """(sid, tid, ts, user_id, event_type, matrix, s_dim, t_dim): streaming targets against static sources, append mode."""
    return _against(visits, zones).withColumn("matrix", verify.matrix_of()).select("sid", "tid", *VISIT, "matrix", "s_dim", "t_dim")


def related_visits(visits: DataFrame, zones: DataFrame) -> DataFrame:
    """(sid, tid, ts, user_id, event_type) of the pairs that share a point.

    Two geometries that fill their boxes share a point just where the boxes do, so such pairs need no matrix. A side of
    static zones that do not fill theirs, and visits that do not, are verified by the kernel.
    """
    columns = ("sid", "tid", *VISIT)
    full = verify.fills_box()
    plain, other = zones.where(full), zones.where(~full)
    out = _against(visits.where(full), plain, BOX).select(*columns)
    out = out.unionByName(related(stream_links(visits.where(~full), plain)).select(*columns))
    return out.unionByName(related(stream_links(visits, other)).select(*columns)) if other.limit(1).count() else out


def left_batches(visits: DataFrame, zones: DataFrame, out: str, checkpoint: str):
    """The left join: related pairs, and each visit without any once with sid null; a folder of out for each micro-batch.

    A visit lies in one micro-batch with all its tiles, so what is unmatched is known within it and no state is kept. Its
    pairs are written once, to where they stay, and read from there for what is unmatched.
    """

    def batch(df: DataFrame, number: int) -> None:
        path = f"{out}/batch={number}"
        links = related_visits(df, zones).select("sid", "tid", "ts")
        links.write.mode("overwrite").parquet(path)
        met = df.sparkSession.read.schema(links.schema).parquet(path).select("tid").distinct()
        alone = df.select(F.lit(None).cast("long").alias("sid"), F.col("gid").alias("tid"), "ts").join(met, "tid", "left_anti").select("sid", "tid", "ts")
        alone.write.mode("append").parquet(path)

    return visits.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def related(links: DataFrame) -> DataFrame:
    return links.where(verify.relation("intersects", F.col("matrix"), F.col("s_dim"), F.col("t_dim")))


def windowed_counts(links: DataFrame, window: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Links per tumbling or sliding window of event time; rows later than the watermark go."""
    w = F.window("ts", window, slide) if slide else F.window("ts", window)
    return links.withWatermark("ts", late).groupBy(w.alias("w")).agg(F.count(F.lit(1)).alias("links")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "links")


def session_counts(links: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    w = F.session_window("ts", gap)
    return links.withWatermark("ts", late).groupBy(w.alias("w"), "user_id").agg(F.count(F.lit(1)).alias("links")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "links")


def without_repeats(visits: DataFrame, late: str = "1 hour") -> DataFrame:
    return visits.withWatermark("ts", late).dropDuplicatesWithinWatermark(["gid"])


def progressive_batches(visits: DataFrame, zones: DataFrame, share: float, out: str, checkpoint: str):
    """Each micro-batch verifies the best `share` of its candidates only: (position, sid, tid, related), a folder a batch."""
    from spatial_links.operators.schedule import Budget, global_top
    from spatial_links.operators.weights import scored

    tile = grid.guarded(grid.mean_tile(zones), zones)

    def batch(df: DataFrame, number: int) -> None:
        best = written(scored(grid.join_tiles(zones, df, tile), "mbro", "js"))
        top = global_top(best, Budget(fraction=share).pairs(best.count()))
        m = verify.matrices(verify.attach(top.select("position", "sid", "tid"), zones, df))
        m.select("position", "sid", "tid", verify.relation("intersects", F.col("matrix"), F.col("s_dim"), F.col("t_dim")).alias("related")).write.mode("overwrite").parquet(f"{out}/batch={number}")
        dropped(best)

    return visits.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def running_totals(links: DataFrame) -> DataFrame:
    """(sid, links, last): links so far of each zone, kept as state across micro-batches."""
    import numpy as np
    import pandas as pd
    import pyarrow as pa
    from pyspark.sql.streaming.state import GroupStateTimeout

    def summed(batches):
        """Sums of a task's links, so that the state gets a row for each zone and task in place of one for each link."""
        held: list[pa.Table] = []

        def once(sums):
            d = pa.concat_tables(held).group_by("sid").aggregate(sums)
            return d.rename_columns([c.removesuffix("_sum").removesuffix("_max") for c in d.column_names]).select(["sid", "ts", "n"])

        for b in batches:
            d = pa.Table.from_batches([b])
            held.append(d.append_column("n", pa.array(np.ones(len(d), np.int64))))
            if sum(map(len, held)) > 1_000_000:
                held = [once([("n", "sum"), ("ts", "max")])]
        if held:
            yield from once([("n", "sum"), ("ts", "max")]).select(["sid", "n", "ts"]).to_batches()

    def update(key, frames, state):
        n, last = state.get if state.exists else (0, pd.Timestamp(0))
        for f in frames:
            n += int(f["n"].sum())
            last = max(last, f["ts"].max())
        state.update((n, last))
        yield pd.DataFrame({"sid": [key[0]], "links": [n], "last": [last]})

    each = links.select("sid", "ts").mapInArrow(summed, "sid long, n long, ts timestamp")
    return each.groupBy("sid").applyInPandasWithState(update, "sid long, links long, last timestamp", "links long, last timestamp", "update", GroupStateTimeout.NoTimeout)


def meetings(first: DataFrame, second: DataFrame, hours: int = 2, late: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: visits of two kinds whose lines share a point within some hours of each other."""
    side = lambda d, p: prefixed(d.withWatermark("ts", late), p, ("xmin", "ymin", "xmax", "ymax", "ts")).withColumnsRenamed({f"{p}_ts": f"{p}ts"})
    a, b = side(first, "s"), side(second, "t")
    a = a.withColumn("sy", F.floor("s_ymin").cast("long"))
    b = b.withColumn("ty", F.floor("t_ymin").cast("long"))
    near = F.expr(f"tts >= sts - interval {hours} hours and tts <= sts + interval {hours} hours")
    return a.join(b, (F.col("sy") == F.col("ty")) & near & boxes_meet()).select("sid", "tid", "sts", "tts")


def run_to_table(stream: DataFrame, path: str, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Runs a stream over all that is there, into files, and returns them.

    append: the file sink. update: all that the batches put out, with their number. complete: the last batch's rows.
    A batch that runs again overwrites its own folder.
    """
    spark, out = stream.sparkSession, f"{path}/out"
    w = stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", checkpoint or f"{path}/checkpoint")
    if mode == "append":
        w.format("parquet").option("path", out).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(out)
    numbers: list[int] = []

    def batch(df: DataFrame, number: int) -> None:
        df.write.mode("overwrite").parquet(f"{out}/batch={number}")
        numbers.append(number)

    w.foreachBatch(batch).start().awaitTermination()
    if not numbers:
        return spark.createDataFrame([], stream.schema)
    if mode == "complete":
        return spark.read.schema(stream.schema).parquet(f"{out}/batch={max(numbers)}")
    return spark.read.parquet(out)
