"""Distributed refinement: label propagation, deterministic swaps, localized searches, flows between block pairs."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import kernels, pairflow
from ..model import Hypergraph
from ..sources.store import truncate_lineage
from . import gains as G
from . import metrics as M
from .prefix import running_sum


def best_moves(h: Hypergraph, p: DataFrame, only: DataFrame | None = None, strictly: bool = True, objective: str = "km1") -> DataFrame:
    """(node, src, dst, gain): each node's best move, ties to the smaller block; positive gains only if ``strictly``."""
    best = G.gains(h, p, only, objective).groupBy("node").agg(F.max(F.struct("gain", (-F.col("block")).alias("tie"))).alias("x"))
    best = best.select("node", (-F.col("x.tie")).cast("int").alias("dst"), F.col("x.gain").alias("gain"))
    best = best.join(p.select("node", F.col("block").alias("src")), "node").select("node", "src", "dst", "gain")
    return best.filter("gain > 0") if strictly else best.filter("gain >= 0")


def numbered(moves: DataFrame) -> DataFrame:
    """Moves in order of gain, then node, as idx, without one task that ranks all: dense ids over (gain, node) packed in order."""
    x = moves.withColumn("_key", F.struct((-F.col("gain")).alias("g"), F.col("node")))
    return running_sum(x.withColumn("_one", F.lit(1)), "_key", "_one", "idx", exclusive=True).select("idx", "node", "src", "dst", "gain")


def lp(h: Hypergraph, p: DataFrame, k: int, eps: float, rounds: int = 3, subrounds: int = 2, seed: int = 0, seeds: DataFrame | None = None, revert_negative: bool = True, objective: str = "km1") -> tuple[DataFrame, list[dict]]:
    """Label propagation: hash shares of the boundary move to their best block together, as far as targets have room.

    The exact gains of the batch in its order decide: moves that turn out negative are taken back, and the whole sub-round if its
    sum still is. ``seeds`` restricts the nodes. Returns the partition and a row a sub-round (round, moved, expected, attributed).
    """
    l_max = M.max_block_weight(M.total_weight(h), k, eps)
    p, log = truncate_lineage(p, "lp"), []
    for r in range(rounds):
        moved = 0
        for s in range(subrounds):
            border = M.boundary_nodes(h, p)
            if seeds is not None:
                border = border.join(seeds.select("node").distinct(), "node", "left_semi")
            mine = border.filter(F.pmod(F.xxhash64("node", F.lit(seed * 100 + r)), F.lit(subrounds)) == s)
            wishes = numbered(truncate_lineage(best_moves(h, p, mine, objective=objective), "wishes"))
            _, ok = G.apply_moves(h, p, wishes, l_max)
            ok = truncate_lineage(ok, "moves")
            exact = truncate_lineage(G.recalculate(h, p, ok, objective).select("idx", "gain"), "exact")
            if revert_negative:
                good = truncate_lineage(ok.join(exact.filter("gain >= 0").select("idx"), "idx", "left_semi"), "kept")
                exact = G.recalculate(h, p, good, objective)
                ok = good
            n, total = exact.agg(F.count("*"), F.coalesce(F.sum("gain"), F.lit(0))).first()
            expected = wishes.join(ok.select("idx"), "idx", "left_semi").agg(F.coalesce(F.sum("gain"), F.lit(0))).first()[0]
            keep = total > 0 and M.block_weights(h, G.moved(p, ok), k, eps).filter("overload > 0").limit(1).count() <= M.block_weights(h, p, k, eps).filter("overload > 0").limit(1).count()
            log.append({"round": r, "subround": s, "moved": n if keep else 0, "expected": expected, "attributed": total if keep else 0})
            if n and keep:
                p = truncate_lineage(G.moved(p, ok), "lp")
                moved += n
        if not moved:
            break
    return p, log


def swaps(wishes: DataFrame, h: Hypergraph, slack: DataFrame) -> DataFrame:
    """Moves (node, src, dst, gain) kept so that every unordered pair of blocks stays within its slack.

    Each side of a pair is ordered by gain, then node, and gets its exclusive prefix weights. Merging both sides by
    that weight is the walk that always takes from the side which has given less; the last feasible step on it is kept.
    ``slack(block, room)``: what each block may still take.
    """
    x = wishes.join(h.nodes, "node").select("node", "src", "dst", "gain", "weight", F.least("src", "dst").alias("s"), F.greatest("src", "dst").alias("t"), (F.col("src") > F.col("dst")).cast("int").alias("side"))
    order = Window.partitionBy("s", "t", "side").orderBy(F.desc("gain"), "node")
    x = x.withColumn("rank", F.row_number().over(order)).withColumn("before", F.coalesce(F.sum("weight").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    walk = Window.partitionBy("s", "t").orderBy("before", "side", "rank")
    signed = F.when(F.col("side") == 0, F.col("weight")).otherwise(-F.col("weight"))
    x = x.withColumn("x", F.sum(signed).over(walk.rowsBetween(Window.unboundedPreceding, 0))).withColumn("step", F.row_number().over(walk))
    room = lambda b, name: slack.select(F.col("block").alias(b), F.col("room").alias(name))
    y = x.join(room("s", "room_s"), "s").join(room("t", "room_t"), "t")
    last = y.filter("x <= room_t and -x <= room_s").groupBy("s", "t").agg(F.max("step").alias("last"))
    return y.join(last, ["s", "t"]).filter(F.col("step") <= F.col("last")).select("node", "src", "dst", "gain")


def slack_of(h: Hypergraph, p: DataFrame, k: int, l_max: int) -> DataFrame:
    """(block, room) for all k blocks."""
    w = M.block_weights(h, p)
    blocks = h.pins.sparkSession.range(k).select(F.col("id").cast("int").alias("block"))
    return blocks.join(w, "block", "left").select("block", F.greatest(F.lit(l_max) - F.coalesce("weight", F.lit(0)), F.lit(0)).cast("long").alias("room"))


def swap_equal_counts(wishes: DataFrame) -> DataFrame:
    """For unit weights: as many moves one way as the other for every pair, best first."""
    x = wishes.select("node", "src", "dst", "gain", F.least("src", "dst").alias("s"), F.greatest("src", "dst").alias("t"))
    x = x.withColumn("rank", F.row_number().over(Window.partitionBy("src", "dst").orderBy(F.desc("gain"), "node")))
    n = x.groupBy("s", "t").agg(F.least(F.count_if(F.col("src") < F.col("dst")), F.count_if(F.col("src") > F.col("dst"))).alias("n"))
    return x.join(n, ["s", "t"]).filter(F.col("rank") <= F.col("n")).select("node", "src", "dst", "gain")


def deterministic_lp(h: Hypergraph, p: DataFrame, k: int, eps: float, rounds: int = 3, subrounds: int = 2, seed: int = 0, objective: str = "km1") -> tuple[DataFrame, list[dict]]:
    """Synchronous label propagation with balance-preserving swaps; the same result for any partitioning of the data.

    Pairs of blocks are spread over rounds of a tournament, so that a block's slack is spent by one pair at a time. A
    sub-round that would not improve is taken back.
    """
    l_max = M.max_block_weight(M.total_weight(h), k, eps)
    p, log = truncate_lineage(p, "det"), []
    now = M.objectives_df(h, p).first()[objective]
    for r in range(rounds):
        gained = 0
        for s in range(subrounds):
            border = M.boundary_nodes(h, p).filter(F.pmod(F.xxhash64("node", F.lit(seed * 100 + r)), F.lit(subrounds)) == s)
            wishes = truncate_lineage(best_moves(h, p, border, objective=objective), "wishes")
            q = p
            for turn in range(max(1, k - 1 + k % 2)):
                part = wishes.filter(G.pair_round(F.col("src"), F.col("dst"), k) == turn)
                q = truncate_lineage(G.moved(q, swaps(part, h, slack_of(h, q, k, l_max))), "det")
            after = M.objectives_df(h, q).first()[objective]
            log.append({"round": r, "subround": s, "before": now, "after": after})
            if after < now:
                gained += now - after
                p, now = q, after
        if not gained:
            break
    return p, log


# -- localized searches -------------------------------------------------------------------------


def regions(h: Hypergraph, p: DataFrame, border: DataFrame, per_search: int = 25, seed: int = 0) -> DataFrame:
    """(node, search): owned nodes of each search.

    Boundary nodes that share their smallest cut net sit together; runs of about ``per_search`` of them, by hash of
    that net, make a search. Neighbours over nets of any size are claimed by the smallest search, so a node is owned once: a net hands on the smallest of its own.
    """
    n = border.count()
    searches = max(1, n // per_search)
    key = h.pins.join(border, "node", "left_semi").groupBy("node").agg(F.min("net").alias("net"))
    own = truncate_lineage(key.select("node", F.pmod(F.xxhash64("net", F.lit(seed)), F.lit(searches)).alias("search"), F.lit(0).alias("hop")), "seeds")
    least = h.pins.join(own, "node").groupBy("net").agg(F.min("search").alias("search"))
    near = h.pins.join(least, "net").select("node", "search", F.lit(1).alias("hop"))
    claim = own.union(near).groupBy("node").agg(F.min(F.struct("hop", "search")).alias("x"))
    return claim.select("node", F.col("x.search").alias("search"), (F.col("x.hop") == 0).alias("seed"))


def fm(h: Hypergraph, p: DataFrame, k: int, eps: float, max_rounds: int = 2, seeds_per_search: int = 25, seed: int = 0, variant: str = "localized", seeds: DataFrame | None = None, objective: str = "km1") -> tuple[DataFrame, list[dict]]:
    """Rounds of localized searches over exclusive regions, one task group a search.

    What a region's nets have outside is frozen for a search: one fixed pin for each outer block. All published moves
    form one sequence, search by search; its exact gains are summed and the best feasible prefix is kept.
    """
    l_max = M.max_block_weight(M.total_weight(h), k, eps)
    p, log = truncate_lineage(p, "fm"), []

    def search(pdf: pd.DataFrame) -> pd.DataFrame:
        owned = pdf[pdf["kind"] == 0].drop_duplicates("node").sort_values("node")
        ids, part = owned["node"].to_numpy(), owned["block"].tolist()
        net_rows = pdf[pdf["kind"] == 1]
        nets = np.unique(net_rows["net"].to_numpy())
        w = net_rows.drop_duplicates("net").sort_values("net")["weight"].tolist()
        n = len(ids)
        pins: list[set[int]] = [set() for _ in nets]
        inner = pdf[pdf["kind"] == 0]
        for e, v in zip(np.searchsorted(nets, inner["net"].to_numpy()).tolist(), np.searchsorted(ids, inner["node"].to_numpy()).tolist(), strict=True):
            pins[e].add(v)
        outer = net_rows[net_rows["outside"] > 0]
        for e, b in zip(np.searchsorted(nets, outer["net"].to_numpy()).tolist(), outer["block"].tolist(), strict=True):
            pins[e].add(n + int(b))
        g = kernels.Local([sorted(vs) for vs in pins], [int(x) for x in w], [*owned["weight"].astype(int).tolist(), *([0] * k)])
        load = [int(x) for x in pdf["load"].iloc[0]]
        starts = np.flatnonzero(owned["seed"].to_numpy()).tolist()
        moves, _ = kernels.localized_fm(g, [*map(int, part), *range(k)], k, [max(l_max, x) for x in load], starts, [True] * n + [False] * k, variant, weight=load, objective=objective)
        return pd.DataFrame({"search": [int(pdf["search"].iloc[0])] * len(moves), "step": list(range(len(moves))), "node": [int(ids[v]) for v, _, _ in moves], "src": [s for _, s, _ in moves], "dst": [t for _, _, t in moves]}).astype({"search": "int64", "step": "int64", "node": "int64", "src": "int32", "dst": "int32"})

    for r in range(max_rounds):
        border = M.boundary_nodes(h, p)
        if seeds is not None:
            border = border.join(seeds.select("node").distinct(), "node", "left_semi")
        own = truncate_lineage(regions(h, p, truncate_lineage(border, "border"), seeds_per_search, seed=seed + r), "owned")
        w = {x["block"]: int(x["weight"]) for x in M.block_weights(h, p).collect()}  # k rows
        load = F.array(*[F.lit(w.get(b, 0)).cast("long") for b in range(k)])
        inner = h.pins.join(own, "node").join(p, "node").join(h.nodes, "node")
        mine = inner.groupBy("search", "net", "block").agg(F.count("*").alias("inside"))
        touched = inner.select("search", "net").distinct()
        around = touched.join(M.pin_counts(h, p), "net").join(mine, ["search", "net", "block"], "left").join(h.nets.select("net", "weight"), "net")
        none = lambda kind: F.lit(None).cast(kind)
        rows = inner.select("search", F.lit(0).alias("kind"), "net", "node", "block", "weight", "seed", none("long").alias("outside")).union(
            around.select("search", F.lit(1).alias("kind"), "net", none("long").alias("node"), "block", "weight", F.lit(False).alias("seed"), (F.col("cnt") - F.coalesce("inside", F.lit(0))).alias("outside"))
        )
        found = truncate_lineage(rows.withColumn("load", load).groupBy("search").applyInPandas(search, "search long, step long, node long, src int, dst int"), "found")
        moves = running_sum(found.withColumn("_key", F.struct("search", "step")).withColumn("_one", F.lit(1)), "_key", "_one", "idx", exclusive=True).select("idx", "node", "src", "dst")
        moves = truncate_lineage(moves, "sequence")
        exact = truncate_lineage(G.recalculate(h, p, moves, objective), "exact")
        best = G.best_prefix(exact, moves, h, p, k, l_max).first()
        n = moves.count()
        log.append({"round": r, "moves": n, "kept": best["idx"] + 1, "gain": best["gain"]})
        if best["gain"] <= 0:
            break
        p = truncate_lineage(G.moved(p, moves.filter(F.col("idx") <= best["idx"])), "fm")
    return p, log


# -- flows --------------------------------------------------------------------------------------


def region_layers(h: Hypergraph, p: DataFrame, bi: int, bj: int, depth: int = 2, max_net_size: int | None = None) -> DataFrame:
    """(node, block, hop): nodes of the two blocks by distance from the cut between them, up to ``depth``."""
    two = p.filter(F.col("block").isin(bi, bj))
    pins = h.pins.join(two, "node")
    cut = pins.groupBy("net").agg(F.count_distinct("block").alias("n")).filter("n = 2").select("net")
    layer = pins.join(cut, "net", "left_semi").select("node", "block").distinct().withColumn("hop", F.lit(0))
    out = layer
    small = pins.join(h.nets.filter(F.col("size") <= max_net_size).select("net"), "net", "left_semi") if max_net_size else pins
    for d in range(1, depth + 1):
        nxt = small.join(layer.select("node"), "node", "left_semi").select("net", "block").distinct().join(small, ["net", "block"]).select("node", "block").distinct()
        layer = nxt.join(out.select("node"), "node", "left_anti").withColumn("hop", F.lit(d))
        out = truncate_lineage(out.union(layer), "layers")
    return out


def network(h: Hypergraph, p: DataFrame, region: DataFrame, bi: int, bj: int) -> DataFrame:
    """(net, vertex, weight) of the flow hypergraph: region nodes keep their ids, the rest of block bi is -1, of bj -2; nets of one vertex are left out."""
    pins = h.pins.join(p.filter(F.col("block").isin(bi, bj)), "node")
    x = pins.join(region.select("node", F.lit(True).alias("inside")), "node", "left")
    v = F.when(F.col("inside"), F.col("node")).when(F.col("block") == bi, F.lit(-1)).otherwise(F.lit(-2))
    y = x.select("net", v.cast("long").alias("vertex")).distinct()
    keep = y.groupBy("net").agg(F.count("*").alias("n"), F.max("vertex").alias("top")).filter("n > 1 and top >= 0 or n = 2").select("net")
    return y.join(keep, "net", "left_semi").join(h.nets.select("net", "weight"), "net")


def expansion(net: DataFrame, cap_pins: bool = True) -> DataFrame:
    """(src, dst, cap) of the expanded network: vertices v0, v1, ..., in-vertices i<net> and out-vertices o<net>."""
    big = F.col("weight") if cap_pins else F.lit(1 << 60)
    node, a, b = F.concat(F.lit("v"), "vertex"), F.concat(F.lit("i"), "net"), F.concat(F.lit("o"), "net")
    bridges = net.select("net", "weight").distinct().select(a.alias("src"), b.alias("dst"), F.col("weight").alias("cap"))
    return bridges.union(net.select(node, a, big.cast("long"))).union(net.select(b, node, big.cast("long")))


def flows(h: Hypergraph, p: DataFrame, k: int, eps: float, max_rounds: int = 2, alpha: float = 16.0, depth: int = 2, min_rel_gain: float = 1e-3, tau: float = 1.0, objective: str = "km1") -> tuple[DataFrame, list[dict]]:
    """Flow refinement of active adjacent block pairs.

    A superstep takes the pairs of one tournament round, which share no block, at most ``tau * k``; each pair's nodes up to ``depth`` hops from
    its cut and what their nets have else in the two blocks go to one group. Moves of a pair whose
    exact joint gain is negative (of ``objective``; the cuts themselves are minimal in connectivity), or that would unbalance, are dropped. A block stays active while it improves;
    rounds end when they gain under a thousandth.
    """
    l_max = M.max_block_weight(M.total_weight(h), k, eps)
    p, log = truncate_lineage(p, "flow"), []
    now, active = M.objectives_df(h, p).first()[objective], set(range(k))

    def solve(pdf: pd.DataFrame) -> pd.DataFrame:
        bi, bj = int(pdf["bi"].iloc[0]), int(pdf["bj"].iloc[0])
        nodes = pdf.drop_duplicates("vertex").sort_values("vertex")
        ids = nodes["vertex"].to_numpy()
        nets = np.unique(pdf["net"].to_numpy())
        pins: list[list[int]] = [[] for _ in nets]
        for e, v in zip(np.searchsorted(nets, pdf["net"].to_numpy()).tolist(), np.searchsorted(ids, pdf["vertex"].to_numpy()).tolist(), strict=True):
            pins[e].append(v)
        net_w = pdf.drop_duplicates("net").sort_values("net")["net_weight"].astype(int).tolist()
        g = kernels.Local(pins, net_w, nodes["node_weight"].astype(int).tolist())
        part = [0 if b == bi else 1 for b in nodes["block"].tolist()]
        moves, expected = pairflow.refine_pair(g, part, 0, 1, [l_max, l_max], alpha, depth, fixed=frozenset(np.flatnonzero(ids < 0).tolist()))
        back = (bi, bj)
        moves = [m for m in moves if ids[m[0]] >= 0]
        return pd.DataFrame({"bi": bi, "bj": bj, "node": [int(ids[v]) for v, _, _ in moves], "src": [back[s] for _, s, _ in moves], "dst": [back[t] for _, _, t in moves], "expected": expected}).astype({"bi": "int32", "bj": "int32", "node": "int64", "src": "int32", "dst": "int32", "expected": "int64"})

    for r in range(max_rounds):
        start, improved = now, set()
        for turn in range(max(1, k - 1 + k % 2)):
            q = M.quotient_graph(h, p).filter(G.pair_round(F.col("bi"), F.col("bj"), k) == turn).filter(F.col("bi").isin(*active) | F.col("bj").isin(*active)) if active else None
            if q is None:
                continue
            pairs = truncate_lineage(q.orderBy(F.desc("weight"), "bi").limit(max(1, int(tau * k))).select("bi", "bj"), "pairs")
            of = pairs.select(F.col("bi").alias("block"), "bi", "bj").union(pairs.select(F.col("bj").alias("block"), "bi", "bj"))
            where = truncate_lineage(p.join(F.broadcast(of), "block"), "where")
            pins = h.pins.join(where, "node")
            cut = pins.groupBy("net", "bi", "bj").agg(F.count_distinct("block").alias("n")).filter("n = 2").select("net", "bi", "bj")
            layer = pins.join(cut, ["net", "bi", "bj"], "left_semi").select("node").distinct()
            inside = layer
            for _ in range(depth):
                layer = pins.join(layer, "node", "left_semi").select("net", "block").distinct().join(pins, ["net", "block"]).select("node").distinct()
                inside = inside.union(layer).distinct()
            inside = truncate_lineage(inside, "inside").withColumn("inside", F.lit(True))
            x = pins.join(inside, "node", "left").join(h.nodes, "node")
            v = F.when(F.col("inside"), F.col("node")).when(F.col("block") == F.col("bi"), -1).otherwise(-2).cast("long")
            x = x.select("bi", "bj", "net", v.alias("vertex"), "block", F.when(F.col("inside"), F.col("weight")).alias("node_weight")).distinct()
            out_w = where.join(inside, "node", "left_anti").join(h.nodes, "node").groupBy("block").agg(F.sum("weight").alias("rest"))
            x = x.join(out_w, "block", "left").withColumn("node_weight", F.coalesce("node_weight", "rest", F.lit(0)).cast("long"))
            keep = x.groupBy("bi", "bj", "net").agg(F.count("*").alias("n")).filter("n > 1").drop("n")
            x = x.join(keep, ["bi", "bj", "net"], "left_semi").join(h.nets.select("net", F.col("weight").alias("net_weight")), "net")
            found = truncate_lineage(x.groupBy("bi", "bj").applyInPandas(solve, "bi int, bj int, node long, src int, dst int, expected long"), "cuts")
            moves = running_sum(found.withColumn("_key", F.struct("bi", "bj", "node")).withColumn("_one", F.lit(1)), "_key", "_one", "idx", exclusive=True)
            moves = truncate_lineage(moves.select("idx", "node", "src", "dst", "bi", "bj", "expected"), "moves")
            real = G.recalculate(h, p, moves.select("idx", "node", "src", "dst"), objective).join(moves.select("idx", "bi", "bj", "expected"), "idx").groupBy("bi", "bj").agg(F.sum("gain").alias("gain"), F.first("expected").alias("expected"))
            rows = real.collect()  # at most k / 2
            good = [(x_["bi"], x_["bj"]) for x_ in rows if x_["gain"] >= 0]
            if good:
                ok = moves.join(F.broadcast(h.pins.sparkSession.createDataFrame(good, "bi int, bj int")), ["bi", "bj"], "left_semi")
                q2 = truncate_lineage(G.moved(p, ok), "flow")
                after = M.objectives_df(h, q2).first()[objective]
                if after <= now and not M.block_weights(h, q2, k, eps).filter("overload > 0").limit(1).count():
                    improved |= {b for x_ in rows if x_["gain"] > 0 for b in (x_["bi"], x_["bj"])}
                    p, now = q2, after
            log += [{"round": r, "turn": turn, "bi": x_["bi"], "bj": x_["bj"], "expected": x_["expected"], "attributed": x_["gain"]} for x_ in rows]
        active = improved
        if start - now < min_rel_gain * max(1, start):
            break
    return p, log
