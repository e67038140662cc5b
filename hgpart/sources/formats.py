"""Text formats of hypergraphs, graphs, sparse matrices and formulas, read with line numbers, and written."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import Hypergraph, build
from ..operators.prefix import running_sum


def _lines(spark: SparkSession, path: str, comment: str) -> DataFrame:
    """(line, text): lines that are not comments, numbered from 0 over one file.

    Files are read whole lines at a time in splits; their order is that of the byte ranges, which Spark numbers by partition.
    """
    raw = spark.read.text(path).select("value", F.monotonically_increasing_id().alias("at"))
    kept = raw.filter((F.trim("value") != "") & ~F.ltrim("value").startswith(comment))
    return running_sum(kept.withColumn("one", F.lit(1)), "at", "one", "line", exclusive=True).select("line", F.col("value").alias("text"))


def _numbers(text: str = "text"):
    return F.transform(F.split(F.trim(text), r"\s+"), lambda x: x.try_cast("long"))


def read_hgr(spark: SparkSession, path: str) -> Hypergraph:
    """Header ``nets nodes [format]`` (1: net weights, 10: node weights, 11: both), a line of 1-based pins a net, then node weights."""
    rows = _lines(spark, path, "%").withColumn("x", _numbers())
    head = rows.filter("line = 0").first()["x"]
    m, n, fmt = head[0], head[1], head[2] if len(head) > 2 else 0
    body = rows.filter((F.col("line") > 0) & (F.col("line") <= m))
    with_net = fmt in (1, 11)
    pins = body.select((F.col("line") - 1).alias("net"), F.explode(F.slice("x", 2 if with_net else 1, F.size("x"))).alias("node")).withColumn("node", F.col("node") - 1)
    nets = body.select((F.col("line") - 1).alias("net"), (F.element_at("x", 1) if with_net else F.lit(1)).cast("long").alias("weight"))
    nodes = spark.range(n).select(F.col("id").alias("node"), F.lit(1).cast("long").alias("weight"))
    if fmt in (10, 11):
        nodes = rows.filter(F.col("line") > m).select((F.col("line") - 1 - m).alias("node"), F.element_at("x", 1).alias("weight"))
    return build(pins, nodes, nets)


def write_hgr(h: Hypergraph, path: str) -> None:
    """One text file of the same form with weights (format 11); nodes and nets must be numbered 0, 1, ..."""
    head = h.nets.agg(F.count("*").alias("m")).crossJoin(h.nodes.agg(F.count("*").alias("n"))).select(F.lit(0).alias("part"), F.lit(0).cast("long").alias("k"), F.concat_ws(" ", "m", "n", F.lit("11")).alias("text"))
    lists = h.pins.groupBy("net").agg(F.array_sort(F.collect_list(F.col("node") + 1)).alias("v")).join(h.nets, "net")
    body = lists.select(F.lit(1).alias("part"), F.col("net").alias("k"), F.concat_ws(" ", F.col("weight").cast("string"), F.transform("v", lambda x: x.cast("string"))).alias("text"))
    tail = h.nodes.select(F.lit(2).alias("part"), F.col("node").alias("k"), F.col("weight").cast("string").alias("text"))
    head.union(body).union(tail).repartitionByRange(1, "part", "k").sortWithinPartitions("part", "k").select("text").write.mode("overwrite").text(path)


def read_graph(spark: SparkSession, path: str) -> DataFrame:
    """(src, dst, weight), 0-based with src < dst. Header ``nodes edges [format]`` (1: edge weights), a line of neighbours a node."""
    rows = _lines(spark, path, "%").withColumn("x", _numbers())
    head = rows.filter("line = 0").first()["x"]
    weighted = len(head) > 2 and head[2] % 10 == 1
    body = rows.filter("line > 0")
    if weighted:
        pair = body.select((F.col("line") - 1).alias("src"), F.posexplode("x").alias("i", "y"), "x").filter("i % 2 = 0").select("src", (F.col("y") - 1).alias("dst"), F.expr("x[i + 1]").alias("weight"))
    else:
        pair = body.select((F.col("line") - 1).alias("src"), F.explode("x").alias("dst")).select("src", (F.col("dst") - 1).alias("dst"), F.lit(1).cast("long").alias("weight"))
    return pair.filter("src < dst")


def read_mtx(spark: SparkSession, path: str, rows_are: str = "nets") -> Hypergraph:
    """Coordinate sparse matrix: row -> its columns as a net (or the transpose)."""
    rows = _lines(spark, path, "%").filter("line > 0").withColumn("x", F.split(F.trim("text"), r"\s+"))
    i, j = F.col("x")[0].cast("long") - 1, F.col("x")[1].cast("long") - 1
    return build(rows.select((i if rows_are == "nets" else j).alias("net"), (j if rows_are == "nets" else i).alias("node")))


def read_cnf(spark: SparkSession, path: str, view: str = "primal") -> Hypergraph:
    """Clauses ``1 -2 0``: primal clause -> variables, literal clause -> literals (2 v, or 2 v + 1 if negated), dual variable -> clauses."""
    rows = _lines(spark, path, "c").filter("line > 0").withColumn("x", F.filter(_numbers(), lambda v: v != 0))
    lit = rows.select((F.col("line") - 1).alias("clause"), F.explode("x").alias("v"))
    var = F.abs("v") - 1
    if view == "literal":
        return build(lit.select(F.col("clause").alias("net"), (var * 2 + (F.col("v") < 0).cast("int")).alias("node")))
    if view == "dual":
        return build(lit.select(var.alias("net"), F.col("clause").alias("node")))
    return build(lit.select(F.col("clause").alias("net"), var.alias("node")))


def read_pins(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """(net, node) from parquet, csv, json or orc."""
    reader = spark.read.schema("net long, node long")
    return reader.csv(path, header=True) if fmt == "csv" else reader.format(fmt).load(path)
