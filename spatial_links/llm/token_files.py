"""Token ids in ORC: stripes of run-length encoded integers with row indexes and Bloom filters on document ids.

The corpus is put in ascending doc_id order by a range partitioning, each partition is encoded and written as one
file. A file holds rows (part, doc_id, row, ids), row being the place in the part; readers take stripes in parallel, and a predicate on doc_id skips
stripes and row groups by their statistics and Bloom filters. Null and empty texts have the end id only; rows that
share a doc_id all stay, in the order in which their file holds them. Rows without a doc_id come first. Other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from spatial_links.llm.common import small
from spatial_links.llm.encode import BLOCK_BYTES, encoder
from spatial_links.llm.textops import blocks

STRIPE_BYTES, INDEX_STRIDE = 64 << 20, 1000
SCHEMA = "part int, doc_id long, row long, ids array<int>"


def _encode(path: str, end_id: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(path, end_id)
        for rows, raw, off in blocks(batches, size=BLOCK_BYTES):
            ids, ends = enc.block(raw, off)
            yield pa.RecordBatch.from_arrays([rows.column(0), pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(ids.view(np.int32)))], names=["doc_id", "ids"])

    return run


def write_tokens(docs: DataFrame, path: str, vocabulary: str, end_id: int, compression: str = "none") -> None:
    """Writes every text of docs(doc_id, text) as ids, in ascending doc_id order, to ORC files under path.

    Run-length encoding packs ids to their bits; a general codec on top (compression) gains little and costs time.
    """
    ordered = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).repartitionByRange("doc_id").sortWithinPartitions("doc_id")
    ids = ordered.mapInArrow(_encode(vocabulary, end_id), "doc_id long, ids array<int>")
    ids = ids.select(F.spark_partition_id().alias("part"), "doc_id", F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1)).alias("row"), "ids")
    options = {"compression": compression, "orc.stripe.size": str(STRIPE_BYTES), "orc.create.index": "true", "orc.row.index.stride": str(INDEX_STRIDE), "orc.bloom.filter.columns": "doc_id", "orc.bloom.filter.fpp": "0.01", "orc.encoding.strategy": "SPEED"}
    ids.write.options(**options).orc(path)


def read_tokens(spark: SparkSession, path: str) -> DataFrame:
    """(part, doc_id, row, ids) of written files; filters on doc_id are pushed down to stripes and row groups."""
    return spark.read.schema(SCHEMA).orc(path)


def _digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        ids = b.column(2)
        off = np.frombuffer(ids.buffers()[1], np.int32)[ids.offset : ids.offset + len(ids) + 1] if len(ids) else np.zeros(1, np.int32)
        raw = memoryview(np.ascontiguousarray(ids.values.to_numpy(zero_copy_only=False).astype("<u4", copy=False))).cast("B")
        crc = [zlib.crc32(raw[4 * int(x) : 4 * int(y)]) for x, y in zip(off[:-1], off[1:], strict=True)]
        yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(3), pa.array(np.diff(off).astype(np.int64)), pa.array(crc, pa.int64())], names=["part", "doc_id", "row", "n_tokens", "ids_crc32"])


def digest(tokens: DataFrame) -> DataFrame:
    """(part, doc_id, row, n_tokens, ids_crc32) of read_tokens' rows."""
    return tokens.select("part", "doc_id", "ids", "row").mapInArrow(_digest, "part int, doc_id long, row long, n_tokens long, ids_crc32 long")


def with_starts(rows: DataFrame) -> DataFrame:
    """Adds start: the ids of all documents before each. One sum per file goes to the driver, the rest stays in its file."""
    sums = rows.groupBy("part").agg(F.sum("n_tokens").alias("n")).orderBy("part").collect()
    before, total = [], 0
    for r in sums:
        before.append((r.part, total))
        total += r.n
    base = small(rows.sparkSession, before, "part int, base long")
    earlier = Window.partitionBy("part").orderBy("row").rowsBetween(Window.unboundedPreceding, -1)
    return rows.join(F.broadcast(base), "part").select("doc_id", (F.col("base") + F.coalesce(F.sum("n_tokens").over(earlier), F.lit(0))).alias("start"), "n_tokens", "ids_crc32")
