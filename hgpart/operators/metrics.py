"""Objectives, balance and structure queries."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import Hypergraph


def total_weight(h: Hypergraph) -> int:
    return int(h.nodes.agg(F.coalesce(F.sum("weight"), F.lit(0))).first()[0])


def max_block_weight(total: int, k: int, eps: float) -> int:
    """Largest whole weight of a block: (1 + eps) * ceil(total / k)."""
    return math.floor((1 + eps) * -(-total // k) + 1e-9)


def block_weights(h: Hypergraph, p: DataFrame, k: int | None = None, eps: float | None = None) -> DataFrame:
    """(block, weight), with ``k`` and ``eps`` also overload = what exceeds the bound."""
    w = h.nodes.join(p, "node").groupBy("block").agg(F.sum("weight").cast("long").alias("weight"))
    if k is None:
        return w
    bound = h.nodes.agg((F.floor((1 + eps) * F.ceil(F.sum("weight") / k) + 1e-9)).cast("long").alias("bound"))
    return w.crossJoin(F.broadcast(bound)).select("block", "weight", F.greatest(F.col("weight") - F.col("bound"), F.lit(0)).cast("long").alias("overload"))


def is_balanced(h: Hypergraph, p: DataFrame, k: int, eps: float) -> bool:
    return not block_weights(h, p, k, eps).filter("overload > 0").limit(1).count()


def pin_counts(h: Hypergraph, p: DataFrame) -> DataFrame:
    """(net, block, cnt): pins of each net in each block that it touches."""
    return h.pins.join(p, "node").groupBy("net", "block").agg(F.count("*").alias("cnt"))


def packed_counts(h: Hypergraph, p: DataFrame, k: int) -> DataFrame:
    """(net, packed): one array of k small counts a net instead of a row a block; two bytes each, which bounds net sizes by 32767 pins in a block."""
    pc = h.pins.join(p, "node").groupBy("net").pivot("block", list(range(k))).agg(F.count("node"))
    return pc.select("net", F.array(*[F.coalesce(F.col(f"`{b}`"), F.lit(0)).cast("smallint") for b in range(k)]).alias("packed"))


def connectivity(pc: DataFrame) -> DataFrame:
    """(net, lambda, blocks) from pin counts; blocks as a sorted list."""
    return pc.groupBy("net").agg(F.count("*").cast("int").alias("lambda"), F.array_sort(F.collect_list("block")).alias("blocks"))


def connectivity_bitset(pc: DataFrame, k: int) -> DataFrame:
    """(net, lambda, mask) with one bit a block; for k up to 63."""
    if k > 63:
        raise ValueError("a bitset holds 63 blocks")
    bits = pc.groupBy("net").agg(F.bit_or(F.expr("shiftleft(1L, block)")).alias("mask"))
    return bits.select("net", F.bit_count("mask").cast("int").alias("lambda"), "mask")


def _lambda(h: Hypergraph, p: DataFrame) -> DataFrame:
    return h.pins.join(p, "node").select("net", "block").distinct().groupBy("net").agg(F.count("*").alias("lambda"))


def cut_nets(h: Hypergraph, p: DataFrame) -> DataFrame:
    return _lambda(h, p).filter("lambda > 1").select("net")


def boundary_nodes(h: Hypergraph, p: DataFrame) -> DataFrame:
    return h.pins.join(cut_nets(h, p), "net", "left_semi").select("node").distinct()


def quotient_graph(h: Hypergraph, p: DataFrame) -> DataFrame:
    """(bi, bj, weight, n): nets that touch both blocks of a pair; at most k a net, so the pairs of a net are bounded by k squared."""
    touched = h.pins.join(p, "node").select("net", "block").distinct()
    a, b = touched.withColumnRenamed("block", "bi"), touched.withColumnRenamed("block", "bj")
    return a.join(b, "net").filter("bi < bj").join(h.nets.select("net", "weight"), "net").groupBy("bi", "bj").agg(F.sum("weight").cast("long").alias("weight"), F.count("*").alias("n"))


def objectives_df(h: Hypergraph, p: DataFrame) -> DataFrame:
    """One row: cut, km1, soed, cut_nets."""
    lam = _lambda(h, p).join(h.nets.select("net", "weight"), "net")
    cut = F.when(F.col("lambda") > 1, F.col("weight")).otherwise(0)
    zero = lambda c: F.coalesce(F.sum(c), F.lit(0)).cast("long")
    return lam.agg(zero(cut).alias("cut"), zero((F.col("lambda") - 1) * F.col("weight")).alias("km1"), zero(cut * F.col("lambda")).alias("soed"), zero((F.col("lambda") > 1).cast("int")).alias("cut_nets"))


def cut(h: Hypergraph, p: DataFrame) -> int:
    return objectives_df(h, p).first()["cut"]


def km1(h: Hypergraph, p: DataFrame) -> int:
    return objectives_df(h, p).first()["km1"]


def soed(h: Hypergraph, p: DataFrame) -> int:
    return objectives_df(h, p).first()["soed"]


def imbalance_df(h: Hypergraph, p: DataFrame, k: int, eps: float) -> DataFrame:
    """One row: imbalance (largest block over ceil(total / k), minus 1) and feasible."""
    w = block_weights(h, p)
    total = h.nodes.agg(F.sum("weight").alias("total"))
    x = w.agg(F.max("weight").alias("top")).crossJoin(total)
    # rounded, so that sums in another order agree
    value = F.round(F.col("top") / F.ceil(F.col("total") / k) - 1, 9)
    return x.select(value.alias("imbalance"), (value <= eps + 1e-9).alias("feasible"))


def imbalance(h: Hypergraph, p: DataFrame, k: int) -> float:
    return float(imbalance_df(h, p, k, 0.0).first()["imbalance"])


def report(h: Hypergraph, p: DataFrame, k: int, eps: float) -> DataFrame:
    return objectives_df(h, p).crossJoin(imbalance_df(h, p, k, eps))


def describe(h: Hypergraph) -> DataFrame:
    """One row of instance statistics."""
    degree = h.pins.groupBy("node").agg(F.count("*").alias("d"))
    size = h.pins.groupBy("net").agg(F.count("*").alias("s"))
    a = h.nodes.agg(F.count("*").alias("nodes"), F.coalesce(F.sum("weight"), F.lit(0)).cast("long").alias("node_weight"))
    b = size.agg(F.count("*").alias("nets"), F.coalesce(F.sum("s"), F.lit(0)).cast("long").alias("pins"), F.percentile("s", F.lit(0.5)).alias("median_size"), F.max("s").alias("max_size"))
    c = degree.agg(F.percentile("d", F.lit(0.5)).alias("median_degree"), F.max("d").alias("max_degree"))
    return a.crossJoin(b).crossJoin(c)


def work_bound(h: Hypergraph, k: int) -> DataFrame:
    """One row: gain-update work sum |e| min(k, |e|) and the sizes of the expanded flow networks."""
    s = F.col("size").cast("long")
    return h.nets.agg(F.sum(s * F.least(s, F.lit(k))).cast("long").alias("gain_updates"), F.sum(2 * s + 1).cast("long").alias("flow_edges"), (F.count("*") * 2).alias("flow_net_nodes"))
