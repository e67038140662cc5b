"""Level store, partition files and lineage cuts in the folder the cluster shares."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        base = held.get() if held.isDefined() else None
    if not base:
        # a folder of one machine will do only where there is one
        local = re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master)
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="hgpart-") if local else spark.conf.get("spark.sql.warehouse.dir") + "/_hgpart")
        base = spark.sparkContext._jsc.sc().getCheckpointDir().get()
    return base.rstrip("/")


def truncate_lineage(df: DataFrame, name: str = "table") -> DataFrame:
    """``df`` stored as Parquet in the shared folder and read back: survives the loss of any executor."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/hgpart-{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def write_level(h, path: str, level: int) -> None:
    """One level of a hierarchy under ``path``, partitioned by level number in the folder names."""
    for name in ("nodes", "nets", "pins"):
        getattr(h, name).write.mode("overwrite").parquet(f"{path}/level={level:03d}/{name}")


def read_level(spark: SparkSession, path: str, level: int):
    from ..model import Hypergraph

    return Hypergraph(*(spark.read.parquet(f"{path}/level={level:03d}/{name}") for name in ("nodes", "nets", "pins")))


def write_partition(blocks: DataFrame, path: str) -> None:
    """(node, block), a folder a block, so that readers of one block prune the rest."""
    blocks.repartition("block").write.mode("overwrite").partitionBy("block").parquet(path)


def write_blocks(blocks: DataFrame, path: str) -> None:
    """One block id a line in ascending order of node, over as many files as ranges."""
    blocks.repartitionByRange("node").sortWithinPartitions("node").select(F.col("block").cast("string")).write.mode("overwrite").text(path)
