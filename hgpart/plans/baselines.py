"""Floors and stand-ins that the presets are compared with."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import arrayflow, arrays, kernels, presets
from ..functions.arrays import Csr, State
from ..model import Hypergraph
from ..operators import contract, initial, metrics, refine
from ..operators.prefix import dense_ids, running_sum
from ..sources.store import truncate_lineage
from .multilevel import PRESETS, partition


def round_robin(h: Hypergraph, k: int) -> DataFrame:
    return h.nodes.select("node", F.pmod("node", F.lit(k)).cast("int").alias("block"))


def hashed(h: Hypergraph, k: int, seed: int = 0, plain: bool = False) -> DataFrame:
    return h.nodes.select("node", F.pmod(_hash(seed, plain), F.lit(k)).cast("int").alias("block"))


def _hash(seed: int, plain: bool):
    """Of a node's id. ``plain``: one that SQL can compute as well; ids that differ by a multiple of k then mostly share a block, so it is no floor for blocks by residue."""
    return F.pmod(F.col("node") * 7919 + 13 + seed * 104729, F.lit(1048573)) if plain else F.xxhash64("node", F.lit(seed))


def random_blocks(h: Hypergraph, k: int, seed: int = 0, plain: bool = False) -> DataFrame:
    """Seeded and balanced by count: nodes in hash order, dealt in turn."""
    ids = dense_ids(h.nodes.select(F.struct(_hash(seed, plain).alias("h"), "node").alias("key")), "key")
    return ids.select("key.node", F.pmod("id", F.lit(k)).cast("int").alias("block"))


def range_blocks(h: Hypergraph, k: int) -> DataFrame:
    """Consecutive ids in k runs of equal count."""
    ids = dense_ids(h.nodes.select("node"), "node")
    n = h.nodes.agg(F.count("*").alias("n"))
    return ids.crossJoin(F.broadcast(n)).select("node", F.expr(f"least(id * {k} div n, {k - 1})").cast("int").alias("block"))


def by_attribute(table: DataFrame, node: str, column: str) -> DataFrame:
    """Blocks by the distinct values of a column, numbered in their order; the values are broadcast if there are up to a million."""
    own = table.select(F.col(node).cast("long").alias("node"), F.col(column).alias("value")).filter("node is not null and value is not null").groupBy("node").agg(F.min("value").alias("value"))
    ids = truncate_lineage(dense_ids(own, "value"), "values")
    return own.join(F.broadcast(ids) if ids.count() <= 1_000_000 else ids, "value").select("node", F.col("id").cast("int").alias("block"))


def exact(h: Hypergraph, k: int, eps: float) -> DataFrame:
    """Best partition by enumeration of up to twelve nodes."""
    if h.nodes.count() > 12:
        raise ValueError("enumeration takes up to twelve nodes")
    a = initial.gather(h)
    g = kernels.Local.of(a["net"], a["node"], a["net_ids"], a["net_weight"], a["node_ids"], a["node_weight"])
    found = kernels.exact(g, k, int(arrays.block_limit(Csr.of(a), k, eps)[0]))
    if found is None:
        raise ValueError("no balanced partition")
    return h.pins.sparkSession.createDataFrame(pd.DataFrame({"node": a["node_ids"], "block": found[1]}), "node long, block int")


def _in_task(h: Hypergraph, k: int, eps: float, f, seed: int) -> DataFrame:
    """``f(g, k, limit, eps, seed)`` in one task, on a hypergraph without copies."""
    h, mapping = contract.without_copies(h, k, eps, least=0)
    a = initial.gather(h)

    def run(value, _):
        g = Csr.of(value)
        return np.asarray(f(g, k, arrays.block_limit(g, k, eps), eps, seed))

    spark = h.pins.sparkSession
    (part,) = initial.tasks(spark, run, [0], a)
    p = spark.createDataFrame(pd.DataFrame({"node": a["node_ids"], "block": part.astype(np.int32)}), "node long, block int")
    return p if mapping is None else contract.project(p, mapping)


def _settled(g, part, k, limit, refine=None, objective="km1"):
    """``part`` refined and balanced."""
    state = State(g, part, k, objective)
    arrays.rebalance(state, limit)
    if refine:
        refine(state, limit)
        arrays.rebalance(state, limit)
    return state.part


def _two(refine, pairs, coarse, objective="km1"):
    """A multilevel bisection by matching or clustering with few initial runs and ``refine`` on every level."""

    def run(g, limit, seed):
        levels, maps, _ = arrays.coarsen(g, coarse, max(1, g.total // coarse), seed, pairs=pairs)
        part = min((arrays.candidate(levels[-1], t, limit, seed) for t in ("fm_global", "max_net_global", "random")), key=lambda x: x[:2])[2]
        for x, to in zip(reversed(levels), [None, *reversed(maps)], strict=True):
            part = _settled(x, part if to is None else part[to], 2, limit, refine, objective)
        return part

    return run


def _recursive(refine, pairs=True, per_block=160, objective="km1", repeats=1):
    """By bisection all the way down, whose imbalances keep the final blocks' bound; the best of ``repeats``."""

    def run(g, k, limit, eps, seed):
        found = [_settled(g, arrays.recursive(g, k, eps, seed + 97 * r, two=_two(refine, pairs, 2 * per_block, objective)), k, limit) for r in range(repeats)]
        return min(found, key=lambda p: g.objective(p, k, objective))

    return run


def _direct(refine, pairs=True, per_block=160, objective="km1", cycles=0, communities=False):
    """Levels by matching or clustering, bisection of the coarsest, ``refine`` on every level; ``cycles`` more times from the blocks found."""

    def run(g, k, limit, eps, seed):
        part, best = None, None
        for c in range(cycles + 1):
            marks = part if c else arrays.louvain(g, seed=seed) if communities else None
            levels, maps, top = arrays.coarsen(g, per_block * k, max(1, g.total // (per_block * k)), seed + c, marks, pairs, bool(c))
            part = top if c else arrays.recursive(levels[-1], k, eps, seed, (1, 1, False))
            for x, to in zip(reversed(levels), [None, *reversed(maps)], strict=True):
                part = _settled(x, part if to is None else part[to], k, limit, refine, objective)
            if best is None or g.objective(part, k, objective) < g.objective(best, k, objective):
                best = part
        return best

    return run


def _steps(*steps):
    def refine(state, limit):
        for f in steps:
            f(state, limit)

    return refine


def _lp(rounds):
    return lambda state, limit: arrays.label_propagation(state, limit, rounds)


def _fm(rounds=1, **options):
    return lambda state, limit: arrays.fm(state, limit, rounds, **options)


def _flow(state, limit):
    arrayflow.refine(state, limit, 1)


def _n_level(per_block=160, flows=False, recursive=False):
    def run(g, k, limit, eps, seed):
        config = replace(PRESETS["quality"], b_max=1, coarse_per_block=per_block, flows=flows, runs=(1, 1, False), lp_rounds=1, fm_rounds=1)
        if recursive:
            two = lambda x, lim, s: presets.whole_run(x, 2, float(lim.max()) * 2 / max(1, x.total) - 1, config, s)[0]
            return _settled(g, arrays.recursive(g, k, eps, seed, two=two), k, limit)
        return presets.whole_run(g, k, eps, config, seed)[0]

    return run


def _flat_lp(g, k, limit, eps, seed):
    return _settled(g, np.arange(g.n) % k, k, limit, _lp(10))


def _flat_kway(g, k, limit, eps, seed):
    """Portfolio bisections of the whole input, without levels."""
    return _settled(g, arrays.recursive(g, k, eps, seed, two=lambda x, lim, s: arrays.portfolio(x, lim, s, (1, 1, False))), k, limit, _lp(3))


def _bfs(g, k, limit, eps, seed):
    two = lambda x, lim, s: arrays.fm2(x, arrays.bfs_grow(x, lim, np.random.default_rng(s)), lim, 1)
    return _settled(g, arrays.recursive(g, k, eps, seed, two=two), k, limit)


def stand_ins(per_block: int = 160) -> dict:
    """name -> f(g, k, limit, eps, seed): one for each method class of the compared systems; the README says what each combines."""
    own = {"per_block": per_block}
    boundary, local = _fm(boundary=True), _fm(2)
    oriented = lambda state, limit: arrays.restricted_lp(state, limit, 3, "oriented")
    paired = lambda state, limit: arrays.restricted_lp(state, limit, 3, "pair_matching")
    return {
        "rb_matching": _recursive(_fm(2), **own),
        "kway_matching": _direct(_lp(3), **own),
        "kway_fast": _direct(boundary, **own),
        "kway_lpclust": _direct(boundary, pairs=False, **own),
        "kway_eco": _direct(_steps(boundary, local), **own),
        "kway_lpclust_eco": _direct(_steps(boundary, local), pairs=False, **own),
        "kway_strong": _direct(_steps(_lp(3), local, _flow), cycles=1, **own),
        "kway_lpclust_strong": _direct(_steps(_lp(3), local, _flow), pairs=False, cycles=1, **own),
        "rb_bfs": _bfs,
        "lp_only": _direct(_lp(3), pairs=False, **own),
        "hill_scanning": _direct(_steps(_lp(3), _fm(2, batch=1, lookahead=16)), **own),
        "oriented_moves": _direct(oriented, **own),
        "fm_local_only": _direct(lambda state, limit: arrays.fm_frozen(state, limit), pairs=False, **own),
        "lp_fast": _direct(_lp(3), pairs=False, **own),
        "lp_eco": _direct(_lp(10), pairs=False, cycles=2, **own),
        "rb_cluster": _recursive(_fm(2), pairs=False, **own),
        "rb_cluster_best": _recursive(_fm(2), pairs=False, repeats=5, **own),
        "rb_matching_soed": _recursive(_fm(2), objective="soed", **own),
        "kway_matching_soed": _direct(_steps(_lp(3), local), objective="soed", **own),
        "n_level": _n_level(per_block),
        "n_level_flows_rb": _n_level(per_block, True, True),
        "n_level_flows": _n_level(per_block, True),
        "pair_matching": _direct(paired, **own),
        "det_matching": _direct(lambda state, limit: arrays.swaps(state, limit), **own),
        "flat_kway": _flat_kway,
    }


STAND_INS = stand_ins()


def stand_in(h: Hypergraph, k: int, eps: float, name: str, seed: int = 0, per_block: int = 160) -> DataFrame:
    return _in_task(h, k, eps, stand_ins(per_block)[name], seed)


def flat_lp(h: Hypergraph, k: int, eps: float, seed: int = 0) -> DataFrame:
    return _in_task(h, k, eps, _flat_lp, seed)


def bfs_grow(h: Hypergraph, k: int, eps: float, seed: int = 0, task_pins: int = initial.TASK_PINS) -> DataFrame:
    """Inputs over ``task_pins`` pins are grown and refined as tables, so that all nets count."""
    if h.pins.count() <= task_pins:
        return _in_task(h, k, eps, _bfs, seed)
    return refine.fm(h, bfs_blocks(h, k, eps, seed), k, eps, 1, seed=seed)[0]


def bfs_layers(pins: DataFrame, state: DataFrame) -> DataFrame:
    """(node, block, at): of every node the label of its component inside its block, the least hash of a node there, and its hops from that node.

    All components of all blocks are walked together, a hop a superstep: the least label comes along with its distance, and its first arrival is the shortest way.
    """
    while True:
        near = pins.join(state.select("node", "at"), "node").groupBy("net", "block").agg(F.min("at").alias("at"))
        got = pins.join(near, ["net", "block"]).groupBy("node").agg(F.min("at").alias("new"))
        step = F.struct(F.col("new.label").alias("label"), (F.col("new.hops") + 1).alias("hops"))
        after = state.withColumnRenamed("at", "old").join(got, "node", "left")
        after = truncate_lineage(after.select("node", "block", F.when(F.col("new").isNull() | (F.col("old") <= step), F.col("old")).otherwise(step).alias("at"), (F.col("new").isNotNull() & (step < F.col("old"))).alias("changed")), "layers")
        state = after.select("node", "block", "at")
        if not after.filter("changed").limit(1).count():
            return state


def bfs_blocks(h: Hypergraph, k: int, eps: float, seed: int = 0) -> DataFrame:
    """(node, block) by bisection, all open blocks together: nodes in order of component, hops and hash fill the first side up to its share."""
    p = truncate_lineage(h.nodes.select("node", F.lit(0).alias("block")), "blocks")
    total, parts = metrics.total_weight(h), {0: k}
    while any(x > 1 for x in parts.values()):
        pins = truncate_lineage(h.pins.join(p.filter(F.col("block").isin([b for b, x in parts.items() if x > 1])), "node"), "open")
        start = p.select("node", "block", F.struct(F.xxhash64("node", F.lit(seed)).alias("label"), F.lit(0).alias("hops")).alias("at"))
        order = F.struct("block", F.col("at.label").alias("label"), F.col("at.hops").alias("hops"), F.xxhash64("node", F.lit(seed + 1)).alias("tie"), "node").alias("key")
        run = running_sum(bfs_layers(pins, start).join(h.nodes, "node").select(order, "weight"), "key", "weight", "run")
        own = {r["block"]: r["w"] for r in run.groupBy("key.block").agg(F.sum("weight").alias("w")).collect()}
        before, rows, nxt = 0, [], {}
        for b, x in sorted(parts.items()):
            w, left = own.get(b, 0), -(-x // 2)
            limit = arrays.bisection_limits(w, x, eps, total, k)
            most = min(w * limit[0] / max(1, limit.sum()), limit[0]) if x > 1 else w
            rows.append((b, float(before + most), left))
            before += w
            nxt |= {b: left} | ({b + left: x - left} if x > 1 else {})
        at = h.pins.sparkSession.createDataFrame(rows, "block int, most double, left int")
        p = truncate_lineage(run.select("key.node", "key.block", "run").join(F.broadcast(at), "block").select("node", (F.col("block") + F.when(F.col("run") > F.col("most"), F.col("left")).otherwise(0)).alias("block")), "blocks")
        parts = nxt
    return p


def default_without_fm(h: Hypergraph, k: int, eps: float, seed: int = 0) -> DataFrame:
    return partition(h, k, eps, config=replace(PRESETS["default"], fm=False), seed=seed).blocks
