"""Weighted hypergraphs as three long tables."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Hypergraph:
    """``nodes(node, weight)``, ``nets(net, weight, size)``, ``pins(net, node)``; a pin occurs once."""

    nodes: DataFrame
    nets: DataFrame
    pins: DataFrame

    def map(self, f) -> Hypergraph:
        return Hypergraph(f(self.nodes), f(self.nets), f(self.pins))

    def materialised(self, name: str = "level") -> Hypergraph:
        """Cut from its lineage: stored in the shared folder and read again."""
        from .sources.store import truncate_lineage

        return Hypergraph(*(truncate_lineage(df, f"{name}-{part}") for df, part in ((self.nodes, "nodes"), (self.nets, "nets"), (self.pins, "pins"))))


def build(pins: DataFrame, nodes: DataFrame | None = None, nets: DataFrame | None = None) -> Hypergraph:
    """Hypergraph of ``pins``; nulls are dropped and repeats collapsed. Missing weights are 1.

    ``nodes(node, weight)`` may name nodes without a net. ``nets(net, weight)`` without a pin are dropped.
    """
    p = pins.select(F.col("net").cast("long"), F.col("node").cast("long")).filter("net is not null and node is not null").distinct()
    n = p.select("node").distinct().withColumn("weight", F.lit(1).cast("long")) if nodes is None else nodes.select(F.col("node").cast("long"), F.col("weight").cast("long"))
    e = p.groupBy("net").agg(F.count("*").cast("int").alias("size"))
    e = e.withColumn("weight", F.lit(1).cast("long")) if nets is None else e.join(nets.select(F.col("net").cast("long"), F.col("weight").cast("long")), "net")
    return Hypergraph(n, e.select("net", "weight", "size"), p)


def induced(h: Hypergraph, nodes: DataFrame, drop_single: bool = True) -> Hypergraph:
    """The part of ``h`` on ``nodes(node)``; nets are cut down to it and kept from two pins on (or one)."""
    keep = nodes.select("node").distinct()
    p = h.pins.join(keep, "node", "left_semi")
    e = p.groupBy("net").agg(F.count("*").cast("int").alias("size")).filter(F.col("size") >= (2 if drop_single else 1))
    e = e.join(h.nets.select("net", "weight"), "net").select("net", "weight", "size")
    return Hypergraph(h.nodes.join(keep, "node", "left_semi"), e, p.join(e.select("net"), "net", "left_semi").select("net", "node"))


def bipartite(h: Hypergraph) -> DataFrame:
    """Edges (src, dst, weight) between nodes (even ids, 2 node) and nets (odd ids, 2 net + 1)."""
    return h.pins.join(h.nets.select("net", "weight"), "net").select((F.col("node") * 2).alias("src"), (F.col("net") * 2 + 1).alias("dst"), "weight")


def to_pinlists(pins: DataFrame) -> DataFrame:
    return pins.groupBy("net").agg(F.array_sort(F.collect_list("node")).alias("nodes"))


def from_pinlists(lists: DataFrame) -> DataFrame:
    return lists.select("net", F.explode("nodes").alias("node"))


def reference_partition(h: Hypergraph, k: int) -> DataFrame:
    """The fixed partition that the SQL checks use."""
    return h.nodes.select("node", F.pmod(F.col("node") * 7919 + 13, F.lit(k)).cast("int").alias("block"))
