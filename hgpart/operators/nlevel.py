"""The contraction forest of the n-level scheme, its time intervals and batches, and pins with validity intervals."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..model import Hypergraph
from ..sources.store import truncate_lineage
from . import coarsen


def admit(candidates: DataFrame, rep: DataFrame, tau: int) -> DataFrame:
    """(node, parent, tau): contractions of one superstep from wishes (node, target): each node at most once and no receiver
    contracted itself, so all of them can share the time ``tau``. Wishes for contracted nodes go to their root (``rep(node, root)``); contracted nodes wish nothing."""
    live = rep.filter("node = root").select("node")
    w = candidates.join(live, "node", "left_semi").join(rep.select(F.col("node").alias("target"), "root"), "target").select("node", F.col("root").alias("target")).filter("node <> target")
    joins = coarsen.resolve_joins(w, "star", seed=tau).filter("node <> rep")
    return joins.select("node", F.col("rep").alias("parent"), F.lit(tau).cast("long").alias("tau"))


def coarsen_forest(h: Hypergraph, k: int, per_block: int = 160, max_passes: int = 60, seed: int = 0, max_net_size: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(node, parent, tau) of all contractions down to ``per_block * k`` roots, and (node, root)."""
    n = h.nodes.count()
    c_max = max(1, int(h.nodes.agg(F.sum("weight")).first()[0]) // (per_block * k))
    rep = truncate_lineage(h.nodes.select("node", F.col("node").alias("root")), "rep")
    forest = None
    for tau in range(max_passes):
        weight = h.nodes.join(rep, "node").groupBy(F.col("root").alias("node")).agg(F.sum("weight").alias("weight"))
        pins = h.pins.join(rep, "node").select("net", F.col("root").alias("node")).distinct()
        sizes = pins.groupBy("net").agg(F.count("*").cast("int").alias("size")).filter("size > 1")
        top = Hypergraph(weight, sizes.join(h.nets.select("net", "weight"), "net"), pins.join(sizes.select("net"), "net", "left_semi")).materialised("pass")
        wishes = coarsen.best_target(coarsen.rate(top, max_net_size=max_net_size), seed=seed + tau)
        heavy = top.nodes.select(F.col("node").alias("target"), F.col("weight").alias("w_t"))
        wishes = wishes.join(heavy, "target").join(top.nodes, "node").filter(F.col("w_t") + F.col("weight") <= c_max).select("node", "target", "rating")
        got = admit(truncate_lineage(wishes, "wishes"), rep, tau)
        # several may join one receiver: the cap holds for them together
        got = truncate_lineage(coarsen.cap(got.select("node", F.col("parent").alias("rep")).union(got.select(F.col("parent").alias("node"), F.col("parent").alias("rep")).distinct()), top.nodes, c_max).filter("node <> rep").select("node", F.col("rep").alias("parent"), F.lit(tau).cast("long").alias("tau")), "admitted")
        c = got.count()
        forest = got if forest is None else truncate_lineage(forest.union(got), "forest")
        if c:
            rep = truncate_lineage(rep.join(got.select(F.col("node").alias("root"), F.col("parent").alias("up")), "root", "left").select("node", F.coalesce("up", "root").alias("root")), "rep")
        n -= c
        if n <= per_block * k or c < 0.01 * n:
            break
    return forest, rep


def sibling_groups(forest: DataFrame) -> DataFrame:
    """(node, parent, grp) from (node, parent, t_start, t_end): siblings whose intervals overlap, also through others, share a number."""
    w = Window.partitionBy("parent").orderBy("t_start", "t_end", "node")
    x = forest.withColumn("reach", F.max("t_end").over(w.rowsBetween(Window.unboundedPreceding, -1)))
    x = x.withColumn("fresh", F.when(F.col("reach").isNull() | (F.col("t_start") > F.col("reach")), 1).otherwise(0))
    return x.select("node", "parent", F.sum("fresh").over(w.rowsBetween(Window.unboundedPreceding, 0)).cast("long").alias("grp"))


def batches(forest: DataFrame, b_max: int = 1000) -> DataFrame:
    """(node, batch): uncontractions in reverse time, of one time together, cut into runs of about ``b_max``.

    Forest rows (node, parent, tau). Contractions of one superstep are independent, so any cut of them is valid; parents were
    contracted later, hence come back strictly earlier.
    """
    from .prefix import running_sum

    x = forest.withColumn("_key", F.struct((-F.col("tau")).alias("t"), F.xxhash64("node").alias("h"), "node")).withColumn("_one", F.lit(1))
    x = running_sum(x, "_key", "_one", "rank", exclusive=True)
    first = x.groupBy("tau").agg(F.min("rank").alias("first"), F.count("*").alias("n"))
    per = first.select("tau", F.ceil(F.col("n") / b_max).alias("runs"))
    rows = sorted(per.collect(), key=lambda r: -r["tau"])  # one row a superstep
    offsets, at = [], 0
    for r in rows:
        offsets.append((r["tau"], at))
        at += r["runs"]
    off = forest.sparkSession.createDataFrame(offsets, "tau long, off long")
    return x.join(F.broadcast(first.join(off, "tau")), "tau").select("node", (F.col("off") + F.floor((F.col("rank") - F.col("first")) / b_max)).cast("long").alias("batch"))


def versioned_pins(h: Hypergraph, forest: DataFrame) -> DataFrame:
    """(net, node, valid_from, valid_to): pins of every visible representative over time; time t is after all contractions with tau < t.

    A pin opens when its node first represents a member in the net and closes when the node is contracted; linear in pins times depth of merging.
    """
    end = forest.select("node", (F.col("tau") + 1).alias("valid_to"))
    up = forest.select("node", "parent", (F.col("tau") + 1).alias("since"))
    forever = F.lit(1 << 62)
    out = layer = truncate_lineage(h.pins.select("net", "node", F.lit(0).cast("long").alias("since")), "pins_v")
    while True:
        nxt = layer.join(up.withColumnRenamed("since", "at"), "node").select("net", F.col("parent").alias("node"), F.col("at").alias("since"))
        nxt = truncate_lineage(nxt.groupBy("net", "node").agg(F.min("since").alias("since")), "pins_v")
        if not nxt.limit(1).count():
            break
        out, layer = out.union(nxt), nxt
    first = truncate_lineage(out.groupBy("net", "node").agg(F.min("since").alias("valid_from")), "pins_v")
    return first.join(end, "node", "left").select("net", "node", "valid_from", F.coalesce("valid_to", forever).alias("valid_to"))


def adjacency_lists(h: Hypergraph) -> DataFrame:
    """(node, nets): every node with a copy of each of its nets and their pins, as plain adjacency lists would hold them; up to quadratic memory, where ``versioned_pins`` is linear."""
    lists = h.pins.groupBy("net").agg(F.array_sort(F.collect_list("node")).alias("pins"))
    return h.pins.join(lists, "net").groupBy("node").agg(F.array_sort(F.collect_list(F.struct("net", "pins"))).alias("nets"))


def adjacency_sizes(h: Hypergraph) -> DataFrame:
    """(node, nets, stored): how many nets and pins ``adjacency_lists`` holds for each node, counted without building the lists."""
    return h.pins.join(h.nets.select("net", "size"), "net").groupBy("node").agg(F.count("*").alias("nets"), F.sum("size").alias("stored"))


def active(pins_v: DataFrame, tau: int) -> DataFrame:
    """(net, node) visible at time ``tau``."""
    return pins_v.filter((F.col("valid_from") <= tau) & (F.col("valid_to") > tau)).select("net", "node")


def roots_at(nodes: DataFrame, forest: DataFrame, tau: int) -> DataFrame:
    """(node, root): the representative of every node after the contractions of all times before ``tau``; pointer doubling."""
    up = forest.filter(F.col("tau") < tau).select("node", "parent")
    root = truncate_lineage(nodes.select("node").join(up, "node", "left").select("node", F.coalesce("parent", "node").alias("root")), "roots")
    while True:
        nxt = truncate_lineage(root.join(root.select(F.col("node").alias("root"), F.col("root").alias("up")), "root").select("node", F.col("up").alias("root"), (F.col("up") != F.col("root")).alias("moved")), "roots")
        root = nxt.select("node", "root")
        if not nxt.filter("moved").limit(1).count():
            return root


def level_at(h: Hypergraph, forest: DataFrame, pins_v: DataFrame, tau: int) -> tuple[Hypergraph, DataFrame]:
    """The hypergraph that is visible at time ``tau``, from versioned pins, and (node, root). Nets of one pin are left out."""
    root = roots_at(h.nodes, forest, tau)
    nodes = h.nodes.join(root, "node").groupBy(F.col("root").alias("node")).agg(F.sum("weight").cast("long").alias("weight"))
    pins = active(pins_v, tau)
    size = pins.groupBy("net").agg(F.count("*").cast("int").alias("size")).filter("size > 1")
    nets = h.nets.select("net", "weight").join(size, "net").select("net", "weight", "size")
    return Hypergraph(nodes, nets, pins.join(nets.select("net"), "net", "left_semi")).materialised("visible"), root


def contract_pair(pins_v: DataFrame, v: int, u: int, tau: int) -> DataFrame:
    """Pins after contracting v onto u at ``tau``: v's open rows close, u's open where it had none."""
    open_ = F.col("valid_to") > tau
    closing = pins_v.filter((F.col("node") == v) & open_)
    had = pins_v.filter((F.col("node") == u) & open_).select("net")
    fresh = closing.join(had, "net", "left_anti").select("net", F.lit(u).cast("long").alias("node"), F.lit(tau).cast("long").alias("valid_from"), "valid_to")
    kept = pins_v.withColumn("valid_to", F.when((F.col("node") == v) & open_, F.lit(tau)).otherwise(F.col("valid_to")).cast("long"))
    return kept.unionByName(fresh)


def uncontract_pair(pins_v: DataFrame, v: int, u: int, tau: int) -> DataFrame:
    """What ``contract_pair`` did at ``tau``, undone."""
    kept = pins_v.filter(~((F.col("node") == u) & (F.col("valid_from") == tau)))
    return kept.withColumn("valid_to", F.when((F.col("node") == v) & (F.col("valid_to") == tau), F.lit(1 << 62)).otherwise(F.col("valid_to")).cast("long"))
