"""Plain graphs: the same methods where every net has two pins. Edges (src, dst, weight), src < dst."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import Hypergraph, build
from ..sources.store import truncate_lineage
from . import coarsen


def arcs(edges: DataFrame) -> DataFrame:
    """Both directions of every edge."""
    return edges.select("src", "dst", "weight").union(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight"))


def neighbours(edges: DataFrame) -> DataFrame:
    """(src, list of (dst, weight)): half the rows of the long form."""
    return arcs(edges).groupBy("src").agg(F.array_sort(F.collect_list(F.struct("dst", "weight"))).alias("near"))


def from_hypergraph(h: Hypergraph) -> DataFrame:
    """Edges of a hypergraph whose nets all have two pins; parallel ones merged."""
    two = h.pins.groupBy("net").agg(F.min("node").alias("src"), F.max("node").alias("dst")).join(h.nets.select("net", "weight"), "net")
    return merge(two.filter("src < dst"))


def to_hypergraph(edges: DataFrame, nodes: DataFrame | None = None) -> Hypergraph:
    e = edges.withColumn("net", F.xxhash64("src", "dst"))
    pins = e.select("net", F.explode(F.array("src", "dst")).alias("node"))
    return build(pins, nodes, e.select("net", "weight"))


def merge(edges: DataFrame) -> DataFrame:
    return edges.groupBy(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).agg(F.sum("weight").cast("long").alias("weight")).filter("src <> dst")


def edge_cut(edges: DataFrame, p: DataFrame) -> DataFrame:
    """One row: cut."""
    a, b = p.select(F.col("node").alias("src"), F.col("block").alias("a")), p.select(F.col("node").alias("dst"), F.col("block").alias("b"))
    return edges.join(a, "src").join(b, "dst").agg(F.coalesce(F.sum(F.when(F.col("a") != F.col("b"), F.col("weight"))), F.lit(0)).cast("long").alias("cut"))


def contract(edges: DataFrame, mapping: DataFrame) -> DataFrame:
    """Edges between clusters: self loops dropped, parallel edges summed."""
    a, b = mapping.select(F.col("node").alias("src"), F.col("coarse").alias("ca")), mapping.select(F.col("node").alias("dst"), F.col("coarse").alias("cb"))
    return merge(edges.join(a, "src").join(b, "dst").select(F.col("ca").alias("src"), F.col("cb").alias("dst"), "weight"))


def gain_table(edges: DataFrame, p: DataFrame) -> DataFrame:
    """(node, block, w): weight from each node into each block that it touches. The gain to t is w(t) - w(own)."""
    return arcs(edges).join(p.select(F.col("node").alias("dst"), "block"), "dst").groupBy(F.col("src").alias("node"), "block").agg(F.sum("weight").cast("long").alias("w"))


def gains(edges: DataFrame, p: DataFrame) -> DataFrame:
    """(node, block, gain) for every other block that a neighbour is in."""
    t = gain_table(edges, p)
    own = p.select("node", F.col("block").alias("own"))
    home = t.join(own, "node").filter("block = own").select("node", F.col("w").alias("home"))
    return t.join(own, "node").filter("block <> own").join(home, "node", "left").select("node", "block", (F.col("w") - F.coalesce("home", F.lit(0))).cast("long").alias("gain"))


def apply_delta(table: DataFrame, edges: DataFrame, p: DataFrame, moves: DataFrame) -> DataFrame:
    """The gain table after ``moves(node, dst)``: each moved node shifts its edge weights at its neighbours; cost the sum of moved degrees."""
    m = moves.select(F.col("node").alias("dst"), F.col("dst").alias("after"))
    x = arcs(edges).join(m, "dst").join(p.select(F.col("node").alias("dst"), F.col("block").alias("before")), "dst")
    d = x.select(F.col("src").alias("node"), F.explode(F.array(F.struct(F.col("before").alias("block"), (-F.col("weight")).alias("d")), F.struct(F.col("after").cast("int").alias("block"), F.col("weight").alias("d")))).alias("s")).select("node", "s.*")
    d = d.groupBy("node", "block").agg(F.sum("d").alias("d"))
    return table.join(d, ["node", "block"], "full").select("node", "block", (F.coalesce("w", F.lit(0)) + F.coalesce("d", F.lit(0))).cast("long").alias("w")).filter("w <> 0")


def attributed(edges: DataFrame, p: DataFrame, moves: DataFrame) -> DataFrame:
    """(idx, node, gain) of moves(idx, node, src, dst) in order: of an edge with both ends moved, the later end sees the earlier one's target."""
    m = moves.select("node", "idx", "dst")
    side = lambda name: m.select(F.col("node").alias(name), F.col("idx").alias(f"i_{name}"), F.col("dst").alias(f"t_{name}"))
    at = lambda name: p.select(F.col("node").alias(name), F.col("block").alias(f"b_{name}"))
    x = edges.join(side("src"), "src", "left").join(side("dst").withColumnRenamed("t_dst", "t_dst"), "dst", "left").filter("i_src is not null or i_dst is not null").join(at("src"), "src").join(at("dst"), "dst")

    def one(me, other):
        there = F.when(F.col(f"i_{other}").isNotNull() & (F.col(f"i_{other}") < F.col(f"i_{me}")), F.col(f"t_{other}")).otherwise(F.col(f"b_{other}"))
        before, after = (F.col(f"b_{me}") != there).cast("int"), (F.col(f"t_{me}") != there).cast("int")
        return F.struct(F.col(f"i_{me}").alias("idx"), ((before - after) * F.col("weight")).alias("g"))

    g = x.select(F.explode(F.array(one("src", "dst"), one("dst", "src"))).alias("s")).select("s.*").filter("idx is not null").groupBy("idx").agg(F.sum("g").alias("g"))
    return moves.select("idx", "node").join(g, "idx", "left").select("idx", "node", F.coalesce("g", F.lit(0)).cast("long").alias("gain"))


def rate(edges: DataFrame, clusters: DataFrame | None = None) -> DataFrame:
    """(node, rep, rating): weight towards each neighbouring cluster."""
    a = arcs(edges)
    if clusters is None:
        return a.select(F.col("src").alias("node"), F.col("dst").alias("rep"), F.col("weight").alias("rating"))
    x = a.join(clusters.select(F.col("node").alias("dst"), "rep"), "dst").join(clusters.select(F.col("node").alias("src"), F.col("rep").alias("own")), "src")
    return x.filter("rep <> own").groupBy(F.col("src").alias("node"), "rep").agg(F.sum("weight").cast("long").alias("rating"))


def coarsen_once(edges: DataFrame, nodes: DataFrame, c_max: int, seed: int = 0) -> DataFrame:
    """(node, rep) after a clustering round on edges alone."""
    wishes = truncate_lineage(coarsen.best_target(rate(edges), seed=seed), "targets")
    joins = coarsen.cap(truncate_lineage(coarsen.resolve_joins(wishes, "star", seed=seed), "joins"), nodes, c_max)
    return nodes.select("node").join(joins, "node", "left").select("node", F.coalesce("rep", "node").alias("rep"))


def partition(edges: DataFrame, k: int, eps: float = 0.03, preset: str = "default", nodes: DataFrame | None = None, seed: int = 0, graph_opt: bool = True, **changes):
    """Partition of a graph for edge cut, which for two-pin nets is the connectivity.

    ``graph_opt``: refinement keeps edges and block weights alone, without pin counts of nets; else it runs on the structures for hypergraphs. Both
    find the same blocks. ``changes`` go to the preset's configuration.
    """
    from dataclasses import replace

    from ..plans import multilevel

    config = replace(multilevel.PRESETS[preset], graph=graph_opt, **changes)
    return multilevel.partition(to_hypergraph(edges, nodes), k, eps, preset, "km1", seed, config)


#: Numbers of the vectors on one side of a pair of blocks, and similarities that a task holds at a time.
BLOCK_VALUES, TILE = 1 << 20, 1 << 20


def _nearest(s: np.ndarray, k: int) -> np.ndarray:
    """Columns of the ``k`` largest of each row, of equal ones the first; -1 where a row has fewer than ``k``."""
    rows, n = s.shape
    if n <= k:
        return np.pad(np.argsort(-s, axis=1, kind="stable"), ((0, 0), (0, k - n)), constant_values=-1)
    least = np.partition(s, n - k, axis=1)[:, n - k, None]
    take, equal = s > least, s == least
    room = k - take.sum(1, keepdims=True)
    more = equal.sum(1, keepdims=True) > room
    if more.any():
        on = more.ravel()
        equal[on] &= np.cumsum(equal[on], axis=1, dtype=np.int32) <= room[on]
    col = np.nonzero(take | equal)[1].reshape(rows, k)
    return np.take_along_axis(col, np.argsort(-np.take_along_axis(s, col, 1), axis=1, kind="stable"), 1)


def knn(vectors: DataFrame, k: int, blocks: int = 8, block_values: int = BLOCK_VALUES, tile: int = TILE) -> DataFrame:
    """(a, b): the k nearest of every vector by cosine (rounded to six digits), ties to the smaller id.

    Exact: vectors are dealt to blocks and every pair of blocks is a task, which keeps k per vector; only those are merged. There are ``blocks``, or as many
    as keep about ``block_values`` numbers in each, and a task compares some rows at a time, so that what it holds does not grow with the table.
    Null vectors are left out.
    """
    v = vectors.filter("id is not null and v is not null").select("id", "v")
    blocks = max(blocks, -(-(v.agg(F.sum(F.size("v"))).first()[0] or 0) // block_values))
    v = v.withColumn("g", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int"))
    pairs = v.select("id", "v", "g", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("o"))
    x = pairs.select("id", "v", F.col("g").alias("bi"), F.col("o").alias("bj"), F.lit(0).alias("side")).union(pairs.select("id", "v", F.col("o"), F.col("g"), F.lit(1)))

    def near(pdf: pd.DataFrame) -> pd.DataFrame:
        a, b = pdf[pdf["side"] == 0].sort_values("id"), pdf[pdf["side"] == 1].sort_values("id")
        if not len(a) or not len(b):
            return pd.DataFrame({"a": [], "b": [], "s": []}).astype({"a": "int64", "b": "int64", "s": "float64"})
        m, n = np.array(a["v"].tolist(), float), np.array(b["v"].tolist(), float)
        m /= np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-300)
        n /= np.maximum(np.linalg.norm(n, axis=1, keepdims=True), 1e-300)
        ida, idb = a["id"].to_numpy(), b["id"].to_numpy()
        found = []
        step = max(1, tile // len(b))
        for at in range(0, len(a), step):
            s = np.round(m[at:at + step] @ n.T, 6)
            own = ida[at:at + step]
            s[own[:, None] == idb[None, :]] = -2
            col = _nearest(s, k)
            row = np.repeat(np.arange(len(own)), k)
            col = col.ravel()
            row, col = row[col >= 0], col[col >= 0]
            got = pd.DataFrame({"a": own[row], "b": idb[col], "s": s[row, col]})
            found.append(got[got["s"] > -2])
        return pd.concat(found)

    best = x.groupBy("bi", "bj").applyInPandas(near, "a long, b long, s double")
    top = best.groupBy("a").agg(F.slice(F.array_sort(F.collect_list(F.struct((-F.col("s")).alias("s"), "b"))), 1, k).alias("x"))
    return top.select("a", F.explode("x.b").alias("b"))
