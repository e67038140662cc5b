"""Shared helpers of the training-data operators."""

from __future__ import annotations

import atexit
import ctypes
import re
import sys
import tempfile
import types
import uuid

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
#: Largest number of rows that a hinted broadcast may hold; callers count first.
BROADCAST_ROWS = 1_000_000
#: Groups with fewer rows are not broadcast where there are more groups than that.
HOT_ROWS = 1_000

_written: list[tuple[SparkSession, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share. Where the session names none: the warehouse on a cluster, a temporary folder in local mode."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        base = held.get() if held.isDefined() else None
    if not base:
        local = re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master)
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="hgpart-") if local else spark.conf.get("spark.sql.warehouse.dir") + "/_hgpart")
        base = spark.sparkContext._jsc.sc().getCheckpointDir().get()
    return base.rstrip("/")


def new_path(spark: SparkSession, name: str) -> str:
    path = f"{shared_dir(spark)}/hgpart-{name}-{uuid.uuid4().hex}"
    _written.append((spark, path))
    return path


@atexit.register
def _remove_written() -> None:
    for spark, path in _written:
        try:
            jvm = spark.sparkContext._jvm
            where = jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
        except Exception:  # the session may have gone before
            return


def written(df: DataFrame, name: str) -> DataFrame:
    """``df`` cut from its lineage: stored as Parquet in the shared folder and read again."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def ascii_lower(text: Column) -> Column:
    """A-Z lower-cased and nothing else; texts of ASCII alone take the built-in's fast path."""
    return F.when(F.octet_length(text) == F.length(text), F.lower(text)).otherwise(F.translate(text, UPPER, UPPER.lower()))


def as_bytes(column: str | Column) -> Column:
    """UTF-8 bytes of a text column; null counts as empty."""
    col = F.col(column) if isinstance(column, str) else column
    return F.coalesce(col.cast("binary"), F.lit(b"").cast("binary"))


def bounded_broadcast(df: DataFrame, rows: int, limit: int = BROADCAST_ROWS) -> DataFrame:
    """Hint a broadcast of ``df`` if its counted ``rows`` stay within ``limit``; otherwise leave the join to Spark."""
    return F.broadcast(df) if rows <= limit else df


def unsent(df: DataFrame, rows: int, limit: int) -> DataFrame:
    """``df`` for joins that Spark may choose freely if its counted ``rows`` stay within ``limit``; otherwise never broadcast, as Spark goes by the size of files and sends far more rows than that."""
    return df if rows <= limit else df.hint("merge")


def join_groups(rows: DataFrame, groups: DataFrame, keys: list[str], count: str, how: str = "inner", limit: int | None = None) -> DataFrame:
    """``rows`` with the columns of their group; ``count`` of ``groups`` says how many rows each has.

    Groups that are few enough (up to ``limit``) are broadcast. Else those with many rows are (their number is bounded by how many rows there are), so that a group of any size
    stays where its rows are, and only the others meet by key.
    """
    n, total = groups.agg(F.count("*"), F.coalesce(F.sum(count), F.lit(0))).first()
    limit = limit or BROADCAST_ROWS
    if n <= limit:
        return rows.join(F.broadcast(groups), keys, how)
    hot = max(HOT_ROWS, -(-total // limit))
    many, few = groups.filter(F.col(count) >= hot), groups.filter(F.col(count) < hot)
    large = rows.join(F.broadcast(many), keys)
    small = rows.join(F.broadcast(many.select(*keys)), keys, "left_anti").join(few.hint("merge"), keys, how)
    return large.unionByName(small)


def worker_cache() -> dict:
    """A dict that lives as long as the Python worker; functions pickled by value have fresh globals for every task."""
    held = sys.modules.get("_hgpart_worker_cache")
    if held is None:
        held = sys.modules["_hgpart_worker_cache"] = types.ModuleType("_hgpart_worker_cache")
        held.items = {}
    return held.items


def small_batches(spark: SparkSession, most: int = 4 << 20) -> None:
    """Let Arrow batches of long texts hold at most 4 MB, so that several workers fit an executor. A setting of queries, not of the start."""
    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    if int(spark.conf.get(name).rstrip("b")) > most:
        spark.conf.set(name, f"{most}b")


def release() -> None:
    """Give memory that the worker has freed back to the system: it may idle beside the next stage's."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        return


def tidy(run):
    """``run`` over the batches of a task, after which its memory is given back."""

    def tidied(batches):
        try:
            yield from run(batches)
        finally:
            release()

    return tidied


def column_stretches(column, size: int = 1 << 20):
    """(first row, Python values) of consecutive stretches of about ``size`` bytes of an Arrow column of bytes or strings."""
    if not len(column):
        return
    ends = np.cumsum(np.nan_to_num(pc.binary_length(column).to_numpy(zero_copy_only=False).astype(float))).astype(np.int64)
    at = 0
    while at < len(column):
        before = int(ends[at - 1]) if at else 0
        to = max(at + 1, int(np.searchsorted(ends, before + size, side="right")))
        yield at, column.slice(at, to - at).to_pylist()
        at = to


def mix64(x: np.ndarray) -> np.ndarray:
    """Bijective 64-bit finaliser on uint64 arrays."""
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xFF51AFD7ED558CCD)
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def connected_components(edges: DataFrame, a: str = "a", b: str = "b", limit: int | None = None) -> DataFrame:
    """Component of every vertex of ``edges``: (node, component), component = smallest node reachable.

    Alternates two contractions until the edges form stars around their
    minima: each vertex hands its larger neighbours to its smallest neighbour,
    then each vertex hands all smaller neighbours (and itself) to the smallest. Both are
    aggregations with map-side minima and equi-joins that Spark may split when
    a vertex is hot; the lineage is cut by a written table in every round.
    Null ends are ignored. No edges give an empty result. Tables of over ``limit`` rows are never broadcast.
    """
    e = edges.select(F.col(a).alias("u"), F.col(b).alias("v")).filter("u is not null and v is not null and u <> v").distinct()
    e = written(e, "cc")
    marks, limit = None, limit or BROADCAST_ROWS
    rows = e.count()
    while True:
        both = e.union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.filter("v > u").join(unsent(least, rows, limit), "u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").distinct()
        large = written(large, "cc")
        # every edge now has u > v
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(unsent(least, rows, limit), "u").select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct("u", F.col("m").alias("v")))).alias("x")).select("x.u", "x.v").filter("u <> v").distinct()
        e = written(small, "cc")
        now = e.agg(F.count("*"), F.coalesce(F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")), F.lit(0))).first()
        if now == marks:
            break
        marks, rows = now, now[0]
    found = e.select(F.col("u").alias("node"), F.col("v").alias("component")).union(e.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
    return unsent(found, rows, limit)
