"""Clustering for coarsening: ratings, targets, conflict resolution, weight caps."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..model import Hypergraph
from ..sources.store import truncate_lineage

#: Ratings are sums of weight * SCALE div (size - 1): whole numbers, so that no order of summing matters.
SCALE = 1 << 20


def rate(h: Hypergraph, clusters: DataFrame | None = None, communities: DataFrame | None = None, max_net_size: int | None = None, only: DataFrame | None = None) -> DataFrame:
    """(node, rep, rating): heavy-edge rating of each node to each cluster that shares a net with it.

    Clusters are collapsed per net before pairs are formed, so a net brings at most (pins x clusters in it)
    rows. ``max_net_size`` leaves large nets out of the rating (they say little: each pair gets weight / (size - 1)).
    With ``communities(node, community)`` both must lie in one. ``only(node)`` restricts the nodes that are rated.
    """
    nets = h.nets.filter("size >= 2")
    if max_net_size is not None:
        nets = nets.filter(F.col("size") <= max_net_size)
    score = nets.select("net", F.expr(f"(weight * {SCALE}L) div (size - 1)").alias("score"))
    pins = h.pins.join(score, "net")
    if communities is not None:
        pins = pins.join(communities, "node")
    side = ["net", "community"] if communities is not None else ["net"]
    own = pins.join(clusters, "node") if clusters is not None else pins.withColumn("rep", F.col("node"))
    targets = own.select(*side, "rep").distinct()
    if clusters is None:
        pins = pins.withColumn("own", F.col("node"))
    else:
        pins = pins.join(clusters.select("node", F.col("rep").alias("own")), "node")
    if only is not None:
        pins = pins.join(only, "node", "left_semi")
    pairs = pins.join(targets, side).filter("own <> rep")
    return pairs.groupBy("node", "rep").agg(F.sum("score").cast("long").alias("rating"))


def best_target(ratings: DataFrame, tie: str = "hash", seed: int = 0) -> DataFrame:
    """(node, target, rating): the highest rating; ties by seeded hash or by the smaller id."""
    order = F.xxhash64("node", "rep", F.lit(seed)) if tie == "hash" else -F.col("rep")
    best = ratings.groupBy("node").agg(F.max(F.struct("rating", order.alias("tie"), "rep")).alias("x"))
    return best.select("node", F.col("x.rep").alias("target"), F.col("x.rating").alias("rating"))


def open_wishes(targets: DataFrame, clustered: DataFrame) -> DataFrame:
    """(node, target): wishes of nodes that are in no cluster yet (``clustered(node, rep)``); a wish for a clustered node goes to its representative."""
    w = targets.select("node", "target").filter("node <> target").join(clustered.select("node"), "node", "left_anti")
    return w.join(clustered.select(F.col("node").alias("target"), "rep"), "target", "left").select("node", F.coalesce("rep", "target").alias("target"))


def resolve_joins(targets: DataFrame, conflict: str = "collapse", clustered: DataFrame | None = None, seed: int = 0) -> DataFrame:
    """(node, rep) for every node that joins another or is joined, from wishes (node, target).

    Wishes of nodes that already belong to a cluster (``clustered(node, rep)``) are dropped, and wishes for such
    nodes go to their representative. ``collapse``: paths join at their end; a cycle is cut at its smallest node b, whose
    target becomes the root. Pointer doubling takes logarithmically many joins. ``star``: one superstep, only wishes
    from seeded joiners to anchors, and of mutual ones the larger joins. ``postprocess``: wishes are applied as they are and afterwards
    nodes whose target itself has moved stay single.
    """
    w = targets.select("node", "target").filter("node <> target")
    if clustered is not None:
        w = open_wishes(w, clustered)
    if conflict == "star":
        coin = lambda c: F.pmod(F.floor((F.col(c) * 7919 + 13 + seed * 104729) / 16), F.lit(2)) == 0
        mutual = w.join(w.select(F.col("node").alias("target"), F.col("target").alias("node")), ["node", "target"]).select("node", F.lit(True).alias("both"))
        x = w.join(mutual, "node", "left")
        join = x.filter(F.when(F.col("both"), F.col("node") > F.col("target")).otherwise(coin("node") & ~coin("target"))).select("node", F.col("target").alias("rep"))
        # an anchor must not join anyone itself
        join = join.join(join.select(F.col("node").alias("rep")), "rep", "left_anti").select("node", "rep")
        return join.union(join.select(F.col("rep").alias("node"), "rep").distinct())
    if conflict == "postprocess":
        join = w.join(w.select(F.col("node").alias("target"), F.col("target").alias("next")), "target", "left")
        join = join.filter("next is null or (next = node and node > target)").select("node", F.col("target").alias("rep"))
        return join.union(join.select(F.col("rep").alias("node"), "rep").distinct())
    roots = w.select(F.col("target").alias("node")).distinct().join(w.select("node"), "node", "left_anti")
    f = w.union(roots.select("node", F.col("node").alias("target")))
    f = truncate_lineage(f.select("node", F.col("target").alias("at"), F.least("node", "target").alias("low")), "pointers")
    wish = truncate_lineage(w, "wishes")
    n = f.count()
    for _ in range(max(1, math.ceil(math.log2(max(2, n))))):
        nxt = f.select(F.col("node").alias("at"), F.col("at").alias("far"), F.col("low").alias("far_low"))
        f = truncate_lineage(f.join(nxt, "at").select("node", F.col("far").alias("at"), F.least("low", "far_low").alias("low")), "pointers")
    # where doubling ends is a root, or a node of the only cycle, whose least node it has seen by then
    ends = f.select("at").distinct().join(roots.select(F.col("node").alias("at"), F.lit(True).alias("root")), "at", "left")
    cycle = f.join(ends.filter("root is null").select("at"), "at", "left_semi").select(F.col("node"), "at", "low")
    on_cycle = cycle.select(F.col("at").alias("node")).distinct().join(f.select("node", "low"), "node")
    root_of = on_cycle.join(wish.select(F.col("node").alias("low"), F.col("target").alias("rep")), "low").select(F.col("node").alias("at"), "rep")
    return f.join(root_of, "at", "left").select("node", F.coalesce("rep", "at").alias("rep"))


def cap(joins: DataFrame, nodes: DataFrame, c_max: int, order: str = "ascending") -> DataFrame:
    """(node, rep) with cluster weights up to ``c_max``: members join in ascending weight (or ``arrival``: id) while they fit.

    Clusters that fit as a whole, nearly all, pass by an aggregation; only the others are ordered, member by member.
    """
    x = joins.join(nodes, "node")
    total = x.groupBy("rep").agg(F.sum("weight").alias("total"))
    own = nodes.select(F.col("node").alias("rep"), F.col("weight").alias("root"))
    fits = x.join(total.filter(F.col("total") <= c_max).select("rep"), "rep", "left_semi").select("node", "rep")
    over = x.join(total.filter(F.col("total") > c_max).select("rep"), "rep", "left_semi").filter("node <> rep").join(own, "rep")
    by = [F.col("weight"), F.col("node")] if order == "ascending" else [F.col("node")]
    running = F.sum("weight").over(Window.partitionBy("rep").orderBy(*by).rowsBetween(Window.unboundedPreceding, 0))
    kept = over.withColumn("running", running).filter(F.col("running") + F.col("root") <= c_max).select("node", "rep")
    return fits.union(kept).union(kept.select(F.col("rep").alias("node"), "rep").distinct())


def matching(h: Hypergraph, communities: DataFrame | None = None) -> DataFrame:
    """(node, rep) of mutually best pairs."""
    t = best_target(rate(h, communities=communities), tie="min_id").select("node", "target")
    back = t.select(F.col("node").alias("target"), F.col("target").alias("node"))
    pairs = t.join(back, ["node", "target"]).filter("node < target")
    return pairs.select("node", F.col("node").alias("rep")).union(pairs.select(F.col("target").alias("node"), F.col("node").alias("rep")))


def limit_round(joins: DataFrame, ratings: DataFrame, n: int, most: float = 2.5) -> DataFrame:
    """Keep the best rated joins so that a round shrinks ``n`` nodes by at most ``most`` times."""
    allowed = n - math.ceil(n / most)
    moving = joins.filter("node <> rep")
    if moving.count() <= allowed:
        return joins
    kept = best_rated(moving.join(ratings.select("node", "rating"), "node", "left").na.fill(0, ["rating"]), allowed).select("node", "rep")
    return kept.union(kept.select(F.col("rep").alias("node"), "rep").distinct())


def deterministic(h: Hypergraph, c_max: int, communities: DataFrame | None = None, subrounds: int = 4, tie: str = "hash", seed: int = 0, max_net_size: int | None = None, most: float = 2.5) -> DataFrame:
    """(node, rep) for all nodes after one round of deterministic clustering: the same for any layout of the data.

    A sub-round takes the single nodes of one share (id * 7919 + 13 + seed modulo ``subrounds``). Each wishes to join its best rated cluster with room, all
    against the clusters that the sub-round found; clustered nodes stay. Of wishes for a node that would itself move, that node stays if a wisher of smaller
    id wants it, else they lapse. Wishes are grouped by target and granted in ascending weight, then id, up to ``c_max``; groups that
    fit as a whole pass without being ordered. A round shrinks the nodes at most ``most`` times.
    """
    n = h.nodes.count()
    left = n - math.ceil(n / most)
    clusters = h.nodes.select("node", F.col("node").alias("rep"), F.lit(True).alias("single"))
    for s in range(subrounds):
        mine = clusters.filter("single").select("node").filter(F.pmod(F.col("node") * 7919 + 13 + seed, F.lit(subrounds)) == s)
        load = clusters.join(h.nodes, "node").groupBy("rep").agg(F.sum("weight").alias("load"))
        first = s == 0
        rated = rate(h, None if first else clusters.select("node", "rep"), communities, max_net_size, mine)
        rated = rated.join(load, "rep").join(h.nodes, "node").filter(F.col("load") + F.col("weight") <= c_max)
        wish = truncate_lineage(best_target(rated, tie, seed), "wishes")
        moving = wish.select(F.col("node").alias("target"), F.lit(True).alias("moving"))
        stays = wish.join(moving, "target").filter(F.col("node") < F.col("target")).select("target").distinct()
        kept = wish.join(stays.select(F.col("target").alias("node")), "node", "left_anti").join(moving, "target", "left").join(stays.withColumn("stays", F.lit(True)), "target", "left")
        kept = kept.filter("moving is null or stays").select("node", F.col("target").alias("rep"), "rating")
        kept = truncate_lineage(kept, "kept")
        count = kept.count()
        if count > left:
            kept = best_rated(kept, left)
        loads = load.select(F.col("rep").alias("node"), F.col("load").alias("weight")).join(kept.select(F.col("rep").alias("node")).distinct(), "node", "left_semi")
        weighed = h.nodes.join(kept.select("node"), "node", "left_semi").union(loads)
        granted = cap(kept.select("node", "rep").union(kept.select(F.col("rep").alias("node"), "rep").distinct()), weighed, c_max)
        granted = truncate_lineage(granted.filter("node <> rep"), "granted")
        used = granted.select("node").union(granted.select(F.col("rep").alias("node"))).distinct().withColumn("used", F.lit(True))
        clusters = clusters.join(granted.withColumnRenamed("rep", "to"), "node", "left").join(used, "node", "left")
        clusters = truncate_lineage(clusters.select("node", F.coalesce("to", "rep").alias("rep"), (F.col("single") & F.col("used").isNull()).alias("single")), "clusters")
        left -= granted.count()
        if left <= 0:
            break
    return clusters.select("node", "rep")


def best_rated(joins: DataFrame, allowed: int) -> DataFrame:
    """The ``allowed`` best rated of ``joins(node, rep, rating)``, then smallest ids, by a prefix sum over ranges."""
    from .prefix import running_sum

    keyed = joins.withColumn("_key", F.struct((-F.col("rating")).alias("r"), "node")).withColumn("_one", F.lit(1))
    return running_sum(keyed, "_key", "_one", "_rank").filter(F.col("_rank") <= allowed).drop("_key", "_one", "_rank")


def should_stop(before: int, now: int, k: int, limit_factor: int = 160) -> bool:
    return now <= limit_factor * k or now > 0.99 * before


def cluster(h: Hypergraph, c_max: int, communities: DataFrame | None = None, conflict: str = "collapse", seed: int = 0, max_net_size: int | None = None, rule: str = "heavy_edge", most: float = 2.5) -> DataFrame:
    """(node, rep) for all nodes after one clustering round, which shrinks them at most ``most`` times."""
    if conflict == "deterministic":
        return deterministic(h, c_max, communities, seed=seed, max_net_size=max_net_size, most=most)
    if rule == "matching":
        joins = matching(h, communities)
    else:
        wishes = truncate_lineage(best_target(rate(h, communities=communities, max_net_size=max_net_size), seed=seed), "targets")
        joins = truncate_lineage(resolve_joins(wishes, conflict, seed=seed), "resolved")
        joins = limit_round(joins, wishes, h.nodes.count(), most)
    joins = cap(truncate_lineage(joins, "joins"), h.nodes, c_max)
    return h.nodes.select("node").join(joins, "node", "left").select("node", F.coalesce("rep", "node").alias("rep"))
