"""Multilevel partitioning: distributed levels while they are large, one task each once they are small."""

from __future__ import annotations

import time
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import presets
from ..model import Hypergraph, induced
from ..operators import coarsen, community, contract, initial, metrics, nlevel, refine
from ..sources.store import truncate_lineage


@dataclass(frozen=True)
class Config:
    """What a preset switches. ``task_pins``: a level with at most so many pins is finished inside tasks. ``seeds``: runs of which the best is taken.

    ``graph``: inputs of two-pin nets alone take the structures for graphs. ``superstep_rounds``: rounds of each refinement on levels that are tables. ``max_net_size``: nets over it take no part in the ratings of such levels
    (each adds a row a pair of its pins or clusters); the log counts them. None: all do.
    """

    deterministic: bool = False
    communities: bool = True
    fm: bool = True
    flows: bool = False
    n_level: bool = False
    b_max: int = 1000
    pairs: bool = False
    fm_boundary: bool = False
    graph: bool = True
    coarse_per_block: int = 160
    runs: tuple[int, int, bool] = presets.RUNS
    seeds: int = 1
    task_pins: int = 1_000_000
    lp_rounds: int = 5
    fm_rounds: int = 3
    superstep_rounds: int = 2
    max_net_size: int | None = None
    conflict: str = "collapse"
    scheme: str = "direct"


PRESETS = {
    "speed_det": Config(deterministic=True, fm=False, runs=presets.FIXED_RUNS, conflict="deterministic"),
    "default": Config(),
    "default_flows": Config(flows=True),
    "quality": Config(n_level=True),
    "quality_flows": Config(n_level=True, flows=True),
}


@dataclass
class PartitionResult:
    blocks: DataFrame
    metrics: DataFrame
    levels: list[dict] = field(default_factory=list)
    log: list[dict] = field(default_factory=list)


def coarsen_levels(h: Hypergraph, k: int, config: Config, seed: int, communities: DataFrame | None, log: list[dict]) -> tuple[list[Hypergraph], list[DataFrame], DataFrame | None]:
    """Hierarchy down to what fits a task or to the contraction limit; the mappings; communities of the last level."""
    levels, maps = [h], []
    total = metrics.total_weight(h)
    c_max = max(1, total // (config.coarse_per_block * k))
    n = h.nodes.count()
    while True:
        top = levels[-1]
        pins = top.pins.count()
        if pins > config.task_pins:
            log.append({"level": len(levels) - 1, "nodes": n, "pins": pins})
        if pins <= config.task_pins or n <= config.coarse_per_block * k:
            return levels, maps, communities
        clusters = truncate_lineage(coarsen.cluster(top, c_max, communities, config.conflict, seed + len(maps), config.max_net_size), "clusters")
        coarse, mapping, _ = contract.contract(top, clusters)
        after = coarse.nodes.count()
        if after > 0.99 * n:
            return levels, maps, communities
        if communities is not None:
            communities = truncate_lineage(mapping.join(communities, "node").groupBy(F.col("coarse").alias("node")).agg(F.min("community").alias("community")), "communities")
        levels.append(coarse)
        maps.append(mapping)
        n = after


def refine_level(h: Hypergraph, p: DataFrame, k: int, eps: float, config: Config, seed: int, log: list[dict], objective: str = "km1") -> DataFrame:
    """One level's refinement as ``config`` switches it, every step for ``objective``."""
    if config.deterministic:
        p, rows = refine.deterministic_lp(h, p, k, eps, config.superstep_rounds, seed=seed, objective=objective)
    else:
        p, rows = refine.lp(h, p, k, eps, config.superstep_rounds, seed=seed, objective=objective)
    log += [{"phase": "lp"} | r for r in rows]
    if config.fm:
        p, rows = refine.fm(h, p, k, eps, config.superstep_rounds, seed=seed, objective=objective)
        log += [{"phase": "fm"} | r for r in rows]
    if config.flows:
        p, rows = refine.flows(h, p, k, eps, objective=objective)
        log += [{"phase": "flows"} | r for r in rows]
    return p


def partition(h: Hypergraph, k: int, eps: float = 0.03, preset: str = "default", objective: str = "km1", seed: int = 0, config: Config | None = None) -> PartitionResult:
    """Blocks 0..k-1 of all nodes, of weight up to (1 + eps) ceil(total / k) each where that can be met.

    Levels above ``task_pins`` pins are clustered, contracted and refined by DataFrame supersteps. The first level
    that fits is partitioned by ``seeds`` independent multilevel runs in as many tasks, of which the best is projected back. Inputs with many copies go without them.
    """
    config = config or PRESETS[preset]
    started, log, levels_log = time.time(), [], []
    h = h.materialised("input")
    small, copies = contract.without_copies(h, k, eps, least=0)
    if copies is not None:
        log.append({"phase": "copies", "seconds": time.time() - started})
        found = partition(small, k, eps, preset, objective, seed, config)
        blocks = truncate_lineage(contract.project(found.blocks, copies), "blocks")
        return PartitionResult(blocks, metrics.report(h, blocks, k, eps), found.levels, log + found.log)
    if config.scheme == "recursive" and k > 2:
        blocks = _recursive(h, k, eps, preset, objective, seed, replace(config, scheme="direct"))
        return PartitionResult(blocks, metrics.report(h, blocks, k, eps), levels_log, log)
    large = h.pins.count() > config.task_pins
    if large and config.n_level:
        p = n_level_tables(h, k, eps, config, objective, seed, log)
        return PartitionResult(p, metrics.report(h, p, k, eps), levels_log, log)
    # below that size the task computes the communities of the run itself
    communities = truncate_lineage(community.louvain(h, seed=seed), "communities") if config.communities and large else None
    if large:
        log.append({"phase": "communities", "seconds": time.time() - started})
    t = time.time()
    levels, maps, communities = coarsen_levels(h, k, config, seed, communities, levels_log)
    if maps:
        log.append({"phase": "coarsening", "seconds": time.time() - t})
    p, rows = initial.best_run(levels[-1], k, eps, config, objective, config.seeds, seed, communities)
    p = truncate_lineage(p, "initial")
    log += [r for r in rows if r["phase"] != "level"]
    levels_log += [{k_: v for k_, v in r.items() if k_ != "phase"} | {"level": r["level"] + len(maps)} for r in rows if r["phase"] == "level" and (r["level"] or not maps)]
    for fine, mapping in zip(reversed(levels[:-1]), reversed(maps), strict=True):
        t = time.time()
        p = refine_level(fine, truncate_lineage(contract.project(p, mapping), "projected"), k, eps, config, seed, log, objective)
        log.append({"phase": "refinement", "seconds": time.time() - t})
    return PartitionResult(p, metrics.report(h, p, k, eps), levels_log, log)


def n_level_tables(h: Hypergraph, k: int, eps: float, config: Config, objective: str, seed: int, log: list[dict]) -> DataFrame:
    """The n-level scheme on tables: a forest of single contractions, admitted superstep by superstep, and pins with validity intervals; no level is stored.

    The coarsest level is partitioned inside tasks. Then each superstep's contractions, which are independent, are undone as one batch: children take their
    parent's block, label propagation and searches start around what came back, with gains set up for the nets they touch, and the whole
    level is refined as in the multilevel scheme.
    """
    t = time.time()
    forest, _ = nlevel.coarsen_forest(h, k, config.coarse_per_block, seed=seed, max_net_size=config.max_net_size)
    forest = truncate_lineage(forest, "forest")
    pins_v = truncate_lineage(nlevel.versioned_pins(h, forest), "versions")
    top = forest.agg(F.coalesce(F.max("tau"), F.lit(-1))).first()[0]
    log.append({"phase": "coarsening", "seconds": time.time() - t})
    level, _ = nlevel.level_at(h, forest, pins_v, top + 1)
    p, rows = initial.best_run(level, k, eps, replace(config, n_level=False), objective, config.seeds, seed)
    p = truncate_lineage(p, "initial")
    log += rows
    for tau in range(top, -1, -1):
        t = time.time()
        back = forest.filter(F.col("tau") == tau)
        p = truncate_lineage(p.union(back.join(p.withColumnRenamed("node", "parent"), "parent").select("node", "block")), "undone")
        level, _ = nlevel.level_at(h, forest, pins_v, tau)
        seeds = truncate_lineage(back.select(F.explode(F.array("node", "parent")).alias("node")).distinct(), "seeds")
        p, rows = refine.lp(level, p, k, eps, 1, seed=seed, seeds=seeds, objective=objective)
        log += [{"phase": "batch lp"} | r for r in rows]
        if config.fm:
            p, rows = refine.fm(level, p, k, eps, 1, seed=seed, seeds=seeds, objective=objective)
            log += [{"phase": "batch fm"} | r for r in rows]
        p = refine_level(level, p, k, eps, config, seed, log, objective)
        log.append({"phase": "refinement", "seconds": time.time() - t})
    return p


def _recursive(h: Hypergraph, k: int, eps: float, preset: str, objective: str, seed: int, config: Config, total: int | None = None, k_all: int | None = None) -> DataFrame:
    """By bisection on whole hypergraphs, each with an imbalance that keeps the final blocks within ``eps``."""
    from ..functions.kernels import adaptive_eps

    own = metrics.total_weight(h)
    total, k_all = total or own, k_all or k
    if k == 1:
        return h.nodes.select("node", F.lit(0).alias("block"))
    e = adaptive_eps(total, k_all, own, k, eps)
    # bounds are whole numbers: a half must not get more than its blocks may have
    e = max(0.0, min(e, metrics.max_block_weight(total, k_all, eps) * (k // 2) / max(1, -(-own // 2)) - 1))
    if k % 2:
        # unequal shares: bisection by ceil and floor of a task's level
        return initial.best_run(h, k, e, config, objective, config.seeds, seed)[0]
    two = partition(h, 2, e, preset, objective, seed, config).blocks
    out = None
    for side in (0, 1):
        part = induced(h, two.filter(F.col("block") == side)).materialised("side")
        inner = _recursive(part, k // 2, eps, preset, objective, seed + 1 + side, config, total, k_all).select("node", (F.col("block") + side * (k // 2)).cast("int").alias("block"))
        out = inner if out is None else out.union(inner)
    return truncate_lineage(out, "recursive")


def vcycle(h: Hypergraph, p: DataFrame, k: int, eps: float, cycles: int = 1, preset: str = "default", seed: int = 0, config: Config | None = None) -> PartitionResult:
    """Coarsen inside the blocks of ``p``, start from it and refine on the way up; the result is never worse."""
    config = config or PRESETS[preset]
    h = h.materialised("input")
    best, value, log = truncate_lineage(p.select("node", F.col("block").cast("int").alias("block")), "start"), metrics.km1(h, p), []
    for c in range(cycles):
        levels, maps, marks = coarsen_levels(h, k, config, seed + c, best.select("node", F.col("block").cast("long").alias("community")), log)
        top = marks.select("node", F.col("community").cast("int").alias("block"))
        q = truncate_lineage(initial.best_run(levels[-1], k, eps, config, "km1", config.seeds, seed + c, start=top)[0], "vcycle")
        for fine, mapping in zip(reversed(levels[:-1]), reversed(maps), strict=True):
            q = refine_level(fine, truncate_lineage(contract.project(q, mapping), "projected"), k, eps, config, seed, log)
        after = metrics.km1(h, q)
        if after < value:
            best, value = q, after
    return PartitionResult(best, metrics.report(h, best, k, eps), log, [])
