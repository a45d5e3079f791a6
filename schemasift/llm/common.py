"""Shared pieces of the corpus operators: table access, durable intermediates, byte views of texts, components."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import re
import tempfile
import uuid
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Python's numeric code works on slices of at most about this many text bytes (one longer text makes a slice of its own).
SLICE_BYTES = 1 << 20
#: So few links are passed on in one partition, without shuffles: their tasks would be nothing but starts.
FEW_LINKS = 10_000


@cache
def lean() -> None:
    """Once in a process: arrays of a megabyte or more, and Arrow's buffers, go back to the system as soon as they are freed. A
    Python worker lives on after its task, and an executor's memory counts what its workers keep."""
    pa.set_memory_pool(pa.system_memory_pool())
    with contextlib.suppress(OSError, AttributeError):  # another C library than glibc
        ctypes.CDLL(None).mallopt(-3, 1 << 20)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share, as the session names it; only a local master, which is one machine, gets one made here."""
    path = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not path:
        if not re.fullmatch(r"local(\[[^\[]*\])?", spark.sparkContext.master):
            raise RuntimeError("spark.checkpoint.dir names no folder that the executors share")
        path = "file://" + tempfile.mkdtemp(prefix="schemasift-")
        spark.sparkContext.setCheckpointDir(path)
    return path.rstrip("/")


def durable(df: DataFrame, name: str) -> DataFrame:
    """Cut the lineage with a written table: executors that die later cost no recomputation."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/schemasift/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def drop_durable(df: DataFrame) -> None:
    """Remove the files of a ``durable`` table that no later plan reads."""
    spark = df.sparkSession
    for name in {f.rsplit("/", 1)[0] for f in df.inputFiles()[:1]}:
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(name)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


#: Names that ``numbered`` adds: the file of a row and its number there.
PLACE = ("__place_file", "__place_row")


def numbered(df: DataFrame) -> DataFrame:
    """df with the place of every row, which tells apart even rows that are equal in all columns. What isn't a plain Parquet
    table is written as one first, so that a place means the same row in every plan, whatever is lost and read again."""
    plain = df._jdf.queryExecution().analyzed()
    if plain.getClass().getSimpleName() != "LogicalRelation" or not all(f.endswith(".parquet") for f in df.inputFiles()) or "_metadata" in df.columns:
        df = durable(df, "numbered")
    return df.select("*", F.col("_metadata.file_path").alias(PLACE[0]), F.col("_metadata.row_index").alias(PLACE[1]))


def release(spark: SparkSession) -> None:
    """Let Spark drop the shuffle files of plans that are done; else they stay until the driver collects its garbage."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def small(df: DataFrame, row_bytes: int, limit: int = 64 << 20) -> DataFrame:
    """df, marked for broadcast only if its rows are counted and known to fit; a larger one is joined by shuffle. df: a written table."""
    return F.broadcast(df) if df.count() * row_bytes <= limit else df


def held_out(doc_id: Column | str) -> Column:
    """True for documents that no model may learn from: crc32 of the id's text leaves 0 modulo 5."""
    doc_id = F.col(doc_id) if isinstance(doc_id, str) else doc_id
    return (F.crc32(F.coalesce(doc_id.cast("string"), F.lit(""))) % 5) == 0


def slices(column: pa.Array | pa.ChunkedArray, limit: int = SLICE_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, UTF-8 bytes, offsets from 0) of a string column; null counts as empty."""
    lean()
    column = pc.fill_null(column, "")
    for chunk in column.chunks if isinstance(column, pa.ChunkedArray) else [column]:
        wide = pa.types.is_large_string(chunk.type) or pa.types.is_large_binary(chunk.type)
        n = len(chunk)
        if not n:
            continue
        at = np.frombuffer(chunk.buffers()[1], dtype=np.int64 if wide else np.int32)[chunk.offset : chunk.offset + n + 1].astype(np.int64)
        data = np.frombuffer(chunk.buffers()[2] or b"", dtype=np.uint8)
        lo = 0
        while lo < n:
            hi = max(lo + 1, int(np.searchsorted(at, at[lo] + limit, side="right")) - 1)
            hi = min(hi, n)
            yield lo, hi, data[at[lo] : at[hi]], at[lo : hi + 1] - at[lo]
            lo = hi


def by_row(values: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Sums of ``values`` between consecutive offsets, empty rows included."""
    total = np.concatenate(([0], np.cumsum(values, dtype=np.int64)))
    return total[offsets[1:]] - total[offsets[:-1]]


def components(edges: DataFrame, name: str = "components") -> DataFrame:
    """(node, root) of every node that has a link; root is the least node of its component.

    Large-star and small-star rounds over the link table, each written to the shared folder. Both are
    a minimum per node and a join, so no task holds the neighbours of a node and hot nodes split in AQE's
    skew join. Rounds over at most ``FEW_LINKS`` links stay in one partition.
    """
    links = durable(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct(), name)
    before, now = None, (links.count(), 0)
    while now != before:
        before = now
        parted = (lambda df: df.coalesce(1)) if now[0] <= FEW_LINKS else (lambda df: df)
        # large star: every larger neighbour of u goes to the least of u and its neighbours
        both = parted(links.union(links.select(F.col("v").alias("u"), F.col("u").alias("v"))))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")
        # small star: u and its smaller neighbours go to the least of them
        large = parted(durable(large.distinct(), name))
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        moved = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        small = durable(parted(moved.union(low.select("u", F.col("m").alias("v")))).distinct(), name)
        drop_durable(links), drop_durable(large)
        links = small
        now = tuple(links.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
    return links.select(F.col("u").alias("node"), F.col("v").alias("root")).union(links.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
