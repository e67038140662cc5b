"""Contraction of clusters, identical-net removal, projection."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import Hypergraph
from .prefix import dense_ids


def renumber(clusters: DataFrame) -> DataFrame:
    """(node, coarse): representatives become 0, 1, ... in ascending order."""
    ids = dense_ids(clusters.select("rep"), "rep", "coarse")
    return clusters.join(ids, "rep").select("node", "coarse")


def coarse_nodes(nodes: DataFrame, mapping: DataFrame) -> DataFrame:
    return nodes.join(mapping, "node").groupBy(F.col("coarse").alias("node")).agg(F.sum("weight").cast("long").alias("weight"))


def coarse_pins(pins: DataFrame, mapping: DataFrame) -> DataFrame:
    return pins.join(mapping, "node").select("net", F.col("coarse").alias("node")).distinct()


def drop_single(nets: DataFrame, pins: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Nets with at least two pins, with their sizes, and the pins of those."""
    size = pins.groupBy("net").agg(F.count("*").cast("int").alias("size")).filter("size >= 2")
    kept = nets.select("net", "weight").join(size, "net")
    return kept.select("net", "weight", "size"), pins.join(kept.select("net"), "net", "left_semi")


def merge_identical(h: Hypergraph, fingerprint: str | None = "sumsq") -> tuple[Hypergraph, DataFrame]:
    """Nets with equal pins become one, the smallest id, with the sum of their weights; and (net, kept).

    Nets are grouped by fingerprint and size first; only those that share both are
    compared pin by pin. ``sumsq``: sum of squared ids as a decimal; ``xx``: sum and xor of 64-bit hashes; None: all are compared.
    """
    node = F.col("node").cast("decimal(38,0)")
    prints = {
        "sumsq": [F.sum(node * node).cast("decimal(38,0)").alias("f")],
        "xx": [F.sum(F.xxhash64("node").cast("decimal(38,0)")).alias("f"), F.bit_xor(F.xxhash64("node")).alias("g")],
        None: [],
    }[fingerprint]
    keys = ["f", "g"][: len(prints)] + ["size"]
    marks = h.pins.groupBy("net").agg(*prints, F.count("*").alias("size"))
    twins = marks.groupBy(*keys).agg(F.count("*").alias("n")).filter("n > 1").drop("n")
    maybe = marks.join(twins, keys).select("net")
    lists = h.pins.join(maybe, "net", "left_semi").groupBy("net").agg(F.array_sort(F.collect_list("node")).alias("v"))
    same = lists.groupBy("v").agg(F.min("net").alias("kept"), F.count("*").alias("n")).filter("n > 1").select("v", "kept")
    merged = lists.join(same, "v").select("net", "kept")
    mapping = h.nets.select("net").join(merged, "net", "left").select("net", F.coalesce("kept", "net").alias("kept"))
    nets = h.nets.join(mapping, "net").groupBy(F.col("kept").alias("net")).agg(F.sum("weight").cast("long").alias("weight"), F.first("size").alias("size"))
    return Hypergraph(h.nodes, nets, h.pins.join(nets.select("net"), "net", "left_semi").select("net", "node")), mapping


def merge_identical_pairs(h: Hypergraph) -> DataFrame:
    """(net, kept) by comparing all pairs of nets of one size and one smallest pin, without fingerprints: the baseline that fingerprints are measured against."""
    lists = h.pins.groupBy("net").agg(F.array_sort(F.collect_list("node")).alias("v"))
    keyed = lists.select("net", "v", F.size("v").alias("size"), F.element_at("v", 1).alias("head"))
    other = keyed.select(F.col("net").alias("other"), F.col("v").alias("u"), "size", "head")
    same = keyed.join(other, ["size", "head"]).filter("v = u").groupBy("net").agg(F.min("other").alias("kept"))
    return h.nets.select("net").join(same, "net", "left").select("net", F.coalesce("kept", "net").alias("kept"))


def contract(h: Hypergraph, clusters: DataFrame, identical: bool = True) -> tuple[Hypergraph, DataFrame, DataFrame]:
    """The coarse hypergraph, (node, coarse) and (net, kept)."""
    from ..sources.store import truncate_lineage

    mapping = truncate_lineage(renumber(clusters), "mapping")
    pins = truncate_lineage(coarse_pins(h.pins, mapping), "coarse")
    nets, pins = drop_single(h.nets, pins)
    coarse = Hypergraph(coarse_nodes(h.nodes, mapping), nets, pins).materialised("single")
    kept = coarse.nets.select("net", F.col("net").alias("kept"))
    if identical:
        coarse, kept = merge_identical(coarse)
        coarse = coarse.materialised("coarse")
    return coarse, mapping, kept


def twins(h: Hypergraph, most: int) -> DataFrame:
    """(node, rep): nodes with the same nets share the smallest of them, in clusters of about half of weight ``most``.

    Nets are compared by two sums of 64-bit hashes and their number. Large groups are dealt by hash, so no task orders one.
    """
    keys = ["f", "g", "n"]
    marks = h.pins.groupBy("node").agg(F.sum(F.xxhash64("net").cast("decimal(38,0)")).alias("f"), F.bit_xor(F.xxhash64("net", F.lit(1))).alias("g"), F.count("*").alias("n")).join(h.nodes, "node")
    groups = marks.groupBy(*keys).agg(F.sum("weight").alias("w"), F.count("*").alias("rows")).filter("rows > 1").select(*keys, F.ceil(F.col("w") * 2 / most).alias("parts"))
    dealt = marks.join(groups, keys).select("node", *keys, F.pmod(F.xxhash64("node"), F.col("parts")).alias("part"))
    first = dealt.groupBy(*keys, "part").agg(F.min("node").alias("rep"))
    return h.nodes.select("node").join(dealt.join(first, [*keys, "part"]).select("node", "rep"), "node", "left").select("node", F.coalesce("rep", "node").alias("rep"))


def without_copies(h: Hypergraph, k: int, eps: float, least: int = 100_000) -> tuple[Hypergraph, DataFrame | None]:
    """``h`` of more than ``least`` pins with twins contracted and identical nets merged, and (node, coarse); ``h`` and None if that saves less than a quarter of the pins.

    A partition of the result has the same objective on ``h``: nets keep their blocks, merged ones add their weights, and nets inside a cluster are never cut. A cluster has
    less weight than a block's room, so balance is not harder to meet; where the room is too small for two nodes, nets alone are merged. Runs pass ``least`` = 0, so that they do the same whatever the size.
    """
    pins = h.pins.count()
    if pins <= least:
        return h, None
    most = int(eps * h.nodes.agg(F.sum("weight")).first()[0] / k / 4)
    coarse, mapping, _ = contract(h, twins(h, most) if most >= 2 else h.nodes.select("node", F.col("node").alias("rep")))
    return (h, None) if coarse.pins.count() > 0.75 * pins else (coarse, mapping)


def project(p: DataFrame, mapping: DataFrame) -> DataFrame:
    """Blocks of the finer nodes."""
    return mapping.join(p.select(F.col("node").alias("coarse"), "block"), "coarse").select("node", "block")
