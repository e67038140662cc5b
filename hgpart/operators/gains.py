"""Gains of moves: from scratch, by deltas, attributed to an order, and exact for sequences."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..model import Hypergraph
from .metrics import pin_counts
from .prefix import running_sum


def gain_table(h: Hypergraph, p: DataFrame) -> tuple[DataFrame, DataFrame]:
    """benefit (node, benefit): weight of nets in which the node is alone in its block; presence (node, block, w_present).

    A net's counts are at most min(size, k) rows, so the join of pins and counts has
    sum |e| min(|e|, k) rows before Spark's partial sums.
    """
    pc = pin_counts(h, p).join(h.nets.select("net", "weight"), "net")
    x = h.pins.join(pc, "net")
    present = x.groupBy("node", "block").agg(F.sum("weight").cast("long").alias("w_present"))
    own = p.select("node", F.col("block").alias("own"))
    alone = F.when(F.col("cnt") == 1, F.col("weight")).otherwise(0)
    benefit = x.join(own, "node").filter("block = own").groupBy("node").agg(F.sum(alone).cast("long").alias("benefit"))
    benefit = h.nodes.select("node").join(benefit, "node", "left").select("node", F.coalesce("benefit", F.lit(0)).alias("benefit"))
    return benefit, present


def block_benefits(h: Hypergraph, p: DataFrame) -> DataFrame:
    """(node, block, benefit): what the node's benefit would be if it sat in each block that its nets touch, others staying."""
    pc = pin_counts(h, p).join(h.nets.select("net", "weight"), "net")
    own = p.select("node", F.col("block").alias("own"))
    x = h.pins.join(pc, "net").join(own, "node")
    # the node itself counts only where it is
    others = F.col("cnt") - F.when(F.col("block") == F.col("own"), 1).otherwise(0)
    return x.groupBy("node", "block").agg(F.sum(F.when(others == 0, F.col("weight")).otherwise(0)).cast("long").alias("benefit"))


def gains(h: Hypergraph, p: DataFrame, only: DataFrame | None = None, objective: str = "km1") -> DataFrame:
    """(node, block, gain) for every other block that one of the node's nets touches; ``only`` restricts the nodes.

    The cut gains by nets that have all other pins in the block, and loses by those that have all pins in the node's own; the sum of external degrees is connectivity and cut together.
    """
    pins = h.pins if only is None else h.pins.join(only.select("node").distinct(), "node", "left_semi")
    pc = pin_counts(h, p).join(h.nets.select("net", "weight", "size"), "net")
    own = p.select("node", F.col("block").alias("own"))
    x = pins.join(own, "node").join(pc, "net")
    weigh = lambda cond, name: F.sum(F.when(cond, F.col("weight")).otherwise(0)).alias(name)
    mine = F.col("block") == F.col("own")
    y = x.groupBy("node", "own", "block").agg(
        F.sum("weight").alias("w"), weigh(mine & (F.col("cnt") == 1), "alone"), weigh(mine & (F.col("cnt") == F.col("size")) & (F.col("size") > 1), "whole"), weigh(~mine & (F.col("cnt") == F.col("size") - 1), "last")
    )
    # each of a node's nets touches its own block, so the row of that block holds the weight of all
    home = y.filter("block = own").select("node", F.col("w").alias("total"), F.col("alone").alias("benefit"), F.col("whole").alias("inside"))
    km1, cut = F.col("benefit") - F.col("total") + F.col("w"), F.col("last") - F.col("inside")
    return y.filter("block <> own").join(home, "node").select("node", "block", {"km1": km1, "cut": cut, "soed": km1 + cut}[objective].cast("long").alias("gain"))


def apply_delta(benefit: DataFrame, present: DataFrame, h: Hypergraph, p: DataFrame, moves: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The gain table after ``moves(node, dst)``, from changes of pin counts alone.

    Only nets with a moved pin and of those only blocks whose count crosses 0, 1 or 2 send changes to their pins; benefits of
    moved nodes are summed anew.
    """
    m = moves.select("node", "dst")
    touched = h.pins.join(m, "node", "left_semi").select("net").distinct()
    pins = h.pins.join(touched, "net", "left_semi").join(p, "node").join(m, "node", "left").select("net", "node", F.col("block").alias("before"), F.coalesce("dst", "block").alias("after")).join(h.nets.select("net", "weight"), "net")
    old = pins.groupBy("net", F.col("before").alias("block")).agg(F.count("*").alias("a"))
    new = pins.groupBy("net", F.col("after").alias("block")).agg(F.count("*").alias("b"))
    phi = old.join(new, ["net", "block"], "full").select("net", "block", F.coalesce("a", F.lit(0)).alias("a"), F.coalesce("b", F.lit(0)).alias("b")).join(h.nets.select("net", "weight"), "net")
    # presence
    step = phi.filter("(a = 0) <> (b = 0)").select("net", "block", F.when(F.col("a") == 0, F.col("weight")).otherwise(-F.col("weight")).alias("d"))
    dp = h.pins.join(step, "net").groupBy("node", "block").agg(F.sum("d").alias("d"))
    present2 = present.join(dp, ["node", "block"], "full").select("node", "block", (F.coalesce("w_present", F.lit(0)) + F.coalesce("d", F.lit(0))).cast("long").alias("w_present")).filter("w_present <> 0")
    # being alone, for nodes that stay
    alone = phi.filter("(a = 1) <> (b = 1)").select("net", "block", F.when(F.col("b") == 1, F.col("weight")).otherwise(-F.col("weight")).alias("d"))
    stay = pins.filter("before = after").select("net", "node", F.col("after").alias("block"))
    db = stay.join(alone, ["net", "block"]).groupBy("node").agg(F.sum("d").alias("d"))
    moved_pins = h.pins.join(m, "node").select("net", "node", F.col("dst").alias("block"))
    fresh = moved_pins.join(phi.filter("b = 1").select("net", "block", "weight"), ["net", "block"]).groupBy("node").agg(F.sum("weight").alias("fresh"))
    moved = m.select("node", F.lit(True).alias("moved"))
    b2 = benefit.join(db, "node", "left").join(moved, "node", "left").join(fresh, "node", "left")
    benefit2 = b2.select("node", F.when(F.col("moved"), F.coalesce("fresh", F.lit(0))).otherwise(F.col("benefit") + F.coalesce("d", F.lit(0))).cast("long").alias("benefit"))
    return benefit2, present2


def recalculate(h: Hypergraph, p: DataFrame, moves: DataFrame, objective: str = "km1") -> DataFrame:
    """(idx, node, gain): exact gains of ``moves(idx, node, src, dst)`` made in order of idx, each node at most once.

    In a net, a block empties when its last move out comes with no pin that stays and none that came before it;
    a block opens at its first move in if nobody was there by then. Both follow from the largest
    out-index, smallest in-index and number of staying pins of each (net, block): one aggregation
    over the pins of touched nets. A net lies whole in a block if all its pins begin or come there, from its last move in to its first move out.
    """
    m = moves.select("idx", "node", "dst")
    touched = h.pins.join(m, "node", "left_semi").select("net").distinct()
    pins = h.pins.join(touched, "net", "left_semi").join(p, "node").join(m, "node", "left")
    moved = F.col("idx").isNotNull()
    sides = pins.select("net", F.explode(F.filter(F.array(
        F.struct(F.col("block"), F.when(moved, F.col("idx")).alias("out"), F.lit(None).cast("long").alias("in"), F.when(moved, 0).otherwise(1).alias("stay")),
        F.when(moved, F.struct(F.col("dst").cast("int").alias("block"), F.lit(None).cast("long").alias("out"), F.col("idx").alias("in"), F.lit(0).alias("stay"))),
    ), lambda s: s.isNotNull())).alias("s")).select("net", "s.*")
    every = sides.groupBy("net", "block").agg(F.max("out").alias("out"), F.min("in").alias("in"), F.sum("stay").alias("stay"), F.count("*").alias("n"), F.max("in").alias("last_in"), F.min("out").alias("first_out"))
    gained = lambda rows, idx: rows.filter(f"{idx} is not null").select(F.col(idx).alias("idx"), F.col("weight").alias("g"))
    lost = lambda rows, idx: rows.filter(f"{idx} is not null").select(F.col(idx).alias("idx"), (-F.col("weight")).alias("g"))
    changes = []
    if objective != "cut":
        each = every.filter("stay = 0").join(h.nets.select("net", "weight"), "net")
        changes += [gained(each.filter("in is null or out < in"), "out"), lost(each.filter("out is null or in > out"), "in")]
    if objective != "km1":
        whole = every.join(h.nets.select("net", "weight", "size"), "net").filter("n = size and size > 1 and (last_in is null or first_out is null or last_in < first_out)")
        changes += [gained(whole, "last_in"), lost(whole, "first_out")]
    g = reduce(DataFrame.union, changes).groupBy("idx").agg(F.sum("g").alias("g"))
    return moves.select("idx", "node").join(g, "idx", "left").select("idx", "node", F.coalesce("g", F.lit(0)).cast("long").alias("gain"))


def attributed(h: Hypergraph, p: DataFrame, moves: DataFrame) -> DataFrame:
    """Attributed gains of a batch: those of its own order. Their sum is the true change."""
    return recalculate(h, p, moves)


def best_prefix(gains_: DataFrame, moves: DataFrame, h: Hypergraph, p: DataFrame, k: int, l_max: int) -> DataFrame:
    """One row: (idx, gain), the feasible prefix of largest total gain (shorter on ties), idx -1 and 0 if none gains.

    After each move only its target can overflow, so a prefix is feasible if no block is above its bound
    (or above its first weight where that was higher): overloads are counted by running sums per block, then over the order.
    """
    x = moves.select("idx", "node", "src", "dst").join(gains_.select("idx", "gain"), "idx").join(h.nodes, "node")
    w0 = h.nodes.join(p, "node").groupBy("block").agg(F.sum("weight").alias("w0"))
    steps = x.select("idx", F.explode(F.array(F.struct(F.col("src").cast("int").alias("block"), (-F.col("weight")).alias("d")), F.struct(F.col("dst").cast("int").alias("block"), F.col("weight").alias("d")))).alias("s")).select("idx", "s.*")
    run = Window.partitionBy("block").orderBy("idx").rowsBetween(Window.unboundedPreceding, 0)
    y = steps.join(w0, "block", "left").withColumn("w0", F.coalesce("w0", F.lit(0))).withColumn("w", F.col("w0") + F.sum("d").over(run))
    bad = (F.col("w") > F.greatest(F.lit(l_max), F.col("w0"))).cast("int")
    before = F.lag(bad, 1, 0).over(Window.partitionBy("block").orderBy("idx"))
    change = y.withColumn("c", bad - before).groupBy("idx").agg(F.sum("c").alias("c"))
    z = running_sum(running_sum(x.join(change, "idx").select("idx", "gain", "c"), "idx", "gain", "total"), "idx", "c", "over")
    best = z.filter("over = 0 and total > 0").agg(F.max(F.struct("total", (-F.col("idx")).alias("neg"))).alias("b"))
    return best.select(F.coalesce(-F.col("b.neg"), F.lit(-1)).cast("long").alias("idx"), F.coalesce("b.total", F.lit(0)).cast("long").alias("gain"))


def apply_moves(h: Hypergraph, p: DataFrame, moves: DataFrame, l_max: int, policy: str = "prefix") -> tuple[DataFrame, DataFrame]:
    """(partition, accepted moves): per target block the longest prefix by idx that fits; weight that leaves is credited only afterwards.

    ``moves(idx, node, src, dst)``. A block's incoming moves are ordered in one window; callers bound them by
    taking sub-rounds.
    """
    w = h.nodes.join(p, "node").groupBy("block").agg(F.sum("weight").alias("w"))
    x = moves.join(h.nodes, "node").join(w.select(F.col("block").alias("dst"), "w"), "dst", "left")
    running = F.sum("weight").over(Window.partitionBy("dst").orderBy("idx").rowsBetween(Window.unboundedPreceding, 0))
    ok = x.withColumn("after", running + F.coalesce("w", F.lit(0))).filter(F.col("after") <= l_max).select("idx", "node", "src", "dst")
    return moved(p, ok), ok


def moved(p: DataFrame, moves: DataFrame) -> DataFrame:
    return p.join(moves.select("node", "dst"), "node", "left").select("node", F.coalesce(F.col("dst").cast("int"), "block").alias("block"))


def deconflict(moves: DataFrame, how: str = "optimistic", k: int | None = None, round_: int = 0, h: Hypergraph | None = None) -> DataFrame:
    """A subset of moves that cannot hurt each other in the sense of ``how``.

    optimistic: all. oriented: only to larger blocks (``round_`` 1: to smaller ones). pair_matching: round ``round_`` of a
    tournament in which every block has one partner. color: nodes that share a net are not both moved; the one with
    the smaller hash, (node * 7919 + 13 + 104729 round) modulo 1048573, stays.
    """
    if how == "optimistic":
        return moves
    if how == "oriented":
        return moves.filter("src < dst" if round_ == 0 else "src > dst")
    if how == "pair_matching":
        return moves.filter(pair_round(F.col("src"), F.col("dst"), k) == round_)
    if how == "color":
        order = F.struct(F.pmod(F.col("node") * 7919 + 13 + 104729 * round_, F.lit(1048573)).alias("h"), "node")
        first = h.pins.join(moves.select("node"), "node", "left_semi").groupBy("net").agg(F.min(order).alias("first"))
        lost = h.pins.join(moves.select("node"), "node", "left_semi").join(first, "net").filter(F.col("first.node") != F.col("node")).select("node")
        return moves.join(lost.distinct(), "node", "left_anti")
    raise ValueError(how)


def pair_round(a, b, k: int):
    """Number of the tournament round in which blocks a and b meet; every block has one partner a round."""
    n = k if k % 2 == 0 else k + 1
    last = F.lit(n - 1)
    lo, hi = F.least(a, b), F.greatest(a, b)
    return F.when(hi == last, F.pmod(2 * lo, last)).otherwise(F.pmod(lo + hi, last)).cast("int")
