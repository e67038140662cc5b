"""Modularity communities on the bipartite graph of nodes and nets, by synchronous local moving in sub-rounds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import Hypergraph
from ..sources.store import truncate_lineage

#: Edge weights are whole multiples of 1 / SCALE, so that sums agree in any order.
SCALE = 1 << 20


def weighted_edges(h: Hypergraph, edge_weight: str = "uniform") -> DataFrame:
    """(src, dst, w): node 2 v and net 2 e + 1, weight(e), or divided by the size, or that times the node's degree; fixed point."""
    nets = h.nets.select("net", "weight", "size")
    x = h.pins.join(nets, "net")
    if edge_weight == "uniform":
        w = F.col("weight") * SCALE
    elif edge_weight == "inverse_size":
        w = F.expr(f"(weight * {SCALE}L) div size")
    elif edge_weight == "degree":
        x = x.join(h.pins.groupBy("node").agg(F.count("*").alias("d")), "node")
        w = F.expr(f"(weight * {SCALE}L * d) div size")
    else:
        raise ValueError(edge_weight)
    return x.select((F.col("node") * 2).alias("src"), (F.col("net") * 2 + 1).alias("dst"), w.cast("long").alias("w"))


def both_ways(edges: DataFrame) -> DataFrame:
    return edges.select("src", "dst", "w").union(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))


def volumes(arcs: DataFrame, comm: DataFrame) -> DataFrame:
    """(community, vol): summed degrees, from scratch."""
    deg = arcs.groupBy("src").agg(F.sum("w").cast("long").alias("deg"))
    return deg.join(comm, deg.src == comm.node).groupBy("community").agg(F.sum("deg").cast("long").alias("vol"))


def volume_delta(vol: DataFrame, moved: DataFrame) -> DataFrame:
    """Volumes after ``moved(node, src, dst, deg)``: changes are listed by node inside each community and folded in that order.

    Degrees are whole numbers here, so the order does not matter; it would for floating point.
    """
    d = moved.select("node", F.col("src").alias("community"), (-F.col("deg")).alias("d")).union(moved.select("node", F.col("dst").alias("community"), F.col("deg").alias("d")))
    fold = F.aggregate(F.array_sort(F.collect_list(F.struct("node", "d"))), F.lit(0).cast("long"), lambda acc, x: acc + x["d"])
    change = d.groupBy("community").agg(fold.alias("d"))
    x = vol.join(change, "community", "full").select("community", (F.coalesce("vol", F.lit(0)) + F.coalesce("d", F.lit(0))).cast("long").alias("vol"))
    return x


def move_round(arcs: DataFrame, comm: DataFrame, degrees: DataFrame, vol: DataFrame, total: int, mine=None) -> DataFrame:
    """(node, src, dst, deg): best strictly positive moves against frozen communities; ties to the smaller community.

    The gain of moving u from A to B, times total squared, is
    2 total (w(u,B) - w(u,A)) - deg (vol(B) - vol(A) + deg), in whole numbers. ``total`` is the sum of all degrees.
    """
    c = comm.select(F.col("node").alias("dst"), "community")
    # what a contracted community has inside goes wherever it goes
    x = arcs.filter("src <> dst").join(c, "dst")
    if mine is not None:
        x = x.filter(mine)
    to = x.groupBy(F.col("src").alias("node"), "community").agg(F.sum("w").cast("decimal(38,0)").alias("w"))
    own = comm.select("node", F.col("community").alias("home"))
    stay = to.join(own, "node").filter("community = home").select("node", F.col("w").alias("w_home"))
    y = to.join(own, "node").filter("community <> home").join(stay, "node", "left").join(degrees, "node")
    y = y.join(vol, "community").join(vol.select(F.col("community").alias("home"), F.col("vol").alias("vol_home")), "home")
    dec = lambda e: e.cast("decimal(38,0)")
    gain = dec((F.col("w") - F.coalesce("w_home", F.lit(0))) * F.lit(total).cast("decimal(19,0)")) - dec(F.col("deg").cast("decimal(18,0)") * (F.col("vol") - F.col("vol_home") + F.col("deg")).cast("decimal(19,0)"))
    y = y.withColumn("gain", gain).filter("gain > 0")
    best = y.groupBy("node").agg(F.max(F.struct("gain", (-F.col("community")).alias("tie"), "home", "deg")).alias("x"))
    return best.select("node", F.col("x.home").alias("src"), (-F.col("x.tie")).alias("dst"), F.col("x.deg").alias("deg"))


def modularity(edges: DataFrame, comm: DataFrame) -> float:
    return float(modularity_df(edges, comm).first()[0])


def modularity_df(edges: DataFrame, comm: DataFrame) -> DataFrame:
    """One row: share of edge weight inside communities minus what degrees alone would put there, to nine digits."""
    a = comm.select(F.col("node").alias("src"), F.col("community").alias("ca"))
    b = comm.select(F.col("node").alias("dst"), F.col("community").alias("cb"))
    x = edges.join(a, "src").join(b, "dst")
    d = lambda c: F.sum(c).cast("double")
    inside = x.agg(d(F.when(F.col("ca") == F.col("cb"), F.col("w")).otherwise(0)).alias("inside"), d("w").alias("m"))
    vol = volumes(both_ways(edges), comm)
    return inside.crossJoin(vol.agg(F.sum(F.col("vol").cast("double") * F.col("vol").cast("double")).alias("sq"))).select(F.round(F.col("inside") / F.col("m") - F.col("sq") / (4 * F.col("m") * F.col("m")), 9).alias("modularity"))


def louvain_graph(edges: DataFrame, subrounds: int = 4, max_rounds: int = 4, max_levels: int = 4, volumes_mode: str = "ordered_delta", seed: int = 0) -> DataFrame:
    """(node, community) for edges (src, dst, w).

    A sub-round moves the hash share of nodes it owns, all at once against what held before. Rounds end when fewer
    than a hundredth of the nodes move; then communities are contracted and moved as wholes.
    """
    top = None
    level_edges = truncate_lineage(edges.select("src", "dst", "w"), "louvain")
    for level in range(max_levels):
        arcs = truncate_lineage(both_ways(level_edges), "arcs")
        degrees = truncate_lineage(arcs.groupBy(F.col("src").alias("node")).agg(F.sum("w").cast("long").alias("deg")), "degrees")
        n, total = degrees.agg(F.count("*"), F.coalesce(F.sum("deg"), F.lit(0))).first()
        if not n:
            break
        comm = truncate_lineage(degrees.select("node", F.col("node").alias("community")), "comm")
        vol = degrees.select(F.col("node").alias("community"), F.col("deg").alias("vol"))
        any_moved = 0
        for rnd in range(max_rounds):
            moved_n = 0
            for s in range(subrounds):
                mine = F.pmod(F.xxhash64("src", F.lit(seed * 1000 + rnd)), F.lit(subrounds)) == s
                moved = truncate_lineage(move_round(arcs, comm, degrees, vol, int(total), mine), "moved")
                c = moved.count()
                if not c:
                    continue
                moved_n += c
                comm = truncate_lineage(comm.join(moved.select("node", "dst"), "node", "left").select("node", F.coalesce("dst", "community").alias("community")), "comm")
                vol = truncate_lineage(volume_delta(vol, moved).filter("vol > 0") if volumes_mode == "ordered_delta" else volumes(arcs, comm), "vol")
            any_moved += moved_n
            if moved_n < max(1, 0.01 * n):
                break
        top = comm if top is None else truncate_lineage(top.select("node", F.col("community").alias("mid")).join(comm.select(F.col("node").alias("mid"), "community"), "mid").select("node", "community"), "top")
        if not any_moved:
            break
        a = comm.select(F.col("node").alias("src"), F.col("community").alias("ca"))
        b = comm.select(F.col("node").alias("dst"), F.col("community").alias("cb"))
        level_edges = truncate_lineage(level_edges.join(a, "src").join(b, "dst").groupBy(F.least("ca", "cb").alias("src"), F.greatest("ca", "cb").alias("dst")).agg(F.sum("w").cast("long").alias("w")), "louvain")
    return top


def louvain(h: Hypergraph, edge_weight: str = "uniform", **options) -> DataFrame:
    """(node, community) of the hypergraph's nodes; nets get communities too, which are dropped. Isolated nodes are their own."""
    comm = louvain_graph(weighted_edges(h, edge_weight), **options)
    own = h.nodes.select("node", (F.col("node") * 2).alias("id"))
    if comm is None:
        return own.select("node", F.col("id").alias("community"))
    return own.join(comm.select(F.col("node").alias("id"), "community"), "id", "left").select("node", F.coalesce("community", "id").alias("community"))
