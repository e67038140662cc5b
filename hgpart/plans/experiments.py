"""The experiments on real runs: a runner that writes a table of runs, and the comparisons that read it."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import arrays, presets
from ..functions.arrays import Csr
from ..model import Hypergraph, from_pinlists
from ..operators import components, initial
from ..sources import workloads as W
from ..sources.store import truncate_lineage
from . import baselines, evaluate
from .catalog import EPS, QUERIES, SQL, over
from .multilevel import PRESETS, partition

RUNS = "instance long, algo long, name string, k int, seed long, threads long, quality long, cut long, soed long, imbalance double, seconds double, status string"
#: Configurations of the algorithms that an experiment can name.
CONFIGS = PRESETS | {"no_fm": replace(PRESETS["default"], fm=False), "no_communities": replace(PRESETS["default"], communities=False)}


def run_one(value, arg) -> tuple:
    """One run in one task: (seconds, km1, cut, soed, heaviest block, log)."""
    g, (name, k, eps, seed, changes) = value, arg
    start = time.perf_counter()
    if name in CONFIGS:
        part, log = presets.whole_run(g, k, eps, replace(CONFIGS[name], **changes), seed)
    else:
        part, log = baselines.stand_ins(changes.get("coarse_per_block", 160))[name](g, k, arrays.block_limit(g, k, eps), eps, seed), []
    took = time.perf_counter() - start
    return took, *(g.objective(part, k, o) for o in ("km1", "cut", "soed")), int(g.weights(part, k).max(initial=0)), log


def sweep(instances: dict[str, Hypergraph], names: list[str], ks: list[int], seeds: list[int], eps: float = EPS, limit: float = 300.0, changes: dict | None = None) -> tuple[DataFrame, DataFrame]:
    """(runs, phases): every algorithm on every instance, k and seed, each run in a task of its own (one thread).

    ``runs`` has the schema that ``evaluate`` reads; instance and algo are numbered in the order given, an (instance, k) being an instance.
    ``phases``: (instance, algo, phase, seconds) of the presets' steps. A run over ``limit`` seconds counts as a timeout.
    """
    rows, steps = [], []
    spark = next(iter(instances.values())).pins.sparkSession
    for i, h in enumerate(instances.values()):
        a = initial.gather(h)
        g = Csr.of(a)
        args = [(n, k, eps, s, changes or {}) for n in names for k in ks for s in seeds]
        for (name, k, _, seed, _), (took, km1, cut, soed, heavy, log) in zip(args, initial.tasks(spark, run_one, args, g), strict=True):
            instance, algo = i * len(ks) + ks.index(k), names.index(name)
            feasible = heavy <= int(arrays.block_limit(g, k, eps)[0])
            status = "timeout" if took > limit else "ok" if feasible else "infeasible"
            rows.append((instance, algo, name, k, seed, 1, km1, cut, soed, heavy / -(-g.total // k) - 1, took, status))
            for r in log:
                if "seconds" in r:
                    steps.append((instance, algo, r["phase"], float(r["seconds"])))
    runs = spark.createDataFrame(rows, RUNS)
    phases = spark.createDataFrame(steps, "instance long, algo long, phase string, seconds double").groupBy("instance", "algo", "phase").agg(F.sum("seconds").alias("seconds"))
    return truncate_lineage(runs, "runs"), truncate_lineage(phases, "phases")


def threads(h: Hypergraph, k: int, counts: list[int], name: str = "default", seed: int = 0, changes: dict | None = None) -> DataFrame:
    """(threads, quality, initial, seconds): one run with its portfolio in 1, 2, ... tasks at a time; the quality doesn't depend on it."""
    spark, a, rows = h.pins.sparkSession, initial.gather(h), []
    config = replace(CONFIGS[name], **(changes or {}))
    for n in counts:
        start = time.perf_counter()
        part, log = initial.one_run(spark, a, k, EPS, config, seed, width=n)
        rows.append((n, Csr.of(a).objective(part, k), sum(r["seconds"] for r in log if r["phase"] == "initial"), time.perf_counter() - start))
    return spark.createDataFrame(rows, "threads long, quality long, initial double, seconds double")


def levels(spark: SparkSession, h: Hypergraph, k: int = 8, name: str = "default", changes: dict | None = None) -> DataFrame:
    """(level, nodes, nets, pins, heaviest, shrink): the hierarchy of one run."""
    got = partition(h, k, EPS, config=replace(CONFIGS[name], **(changes or {"coarse_per_block": 16, "runs": (1, 1, False)}))).levels
    rows = [(r["level"], r["nodes"], r.get("nets"), r["pins"], r.get("heaviest"), got[i - 1]["nodes"] / r["nodes"] if i else None) for i, r in enumerate(got)]
    return spark.createDataFrame(rows, "level long, nodes long, nets long, pins long, heaviest long, shrink double")


def work_done(spark: SparkSession, f: Callable[[], object]) -> dict[str, int]:
    """Bytes that ``f`` shuffled and spilled and the largest task's peak memory, from the stages that Spark has run for it."""
    store = spark.sparkContext._jsc.sc().statusStore()

    def stages():
        found, at = {}, store.stageList(None, False, False, spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.double, 0), None)
        for i in range(at.size()):
            s = at.apply(i)
            found[s.stageId(), s.attemptId()] = (s.shuffleWriteBytes(), s.shuffleReadBytes(), s.memoryBytesSpilled() + s.diskBytesSpilled(), s.peakExecutionMemory())
        return found

    before = stages()
    f()
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
    new = [v for k, v in stages().items() if k not in before]
    return {"stages": len(new), "shuffle_written": sum(v[0] for v in new), "shuffle_read": sum(v[1] for v in new), "spilled": sum(v[2] for v in new), "peak_memory": max((v[3] for v in new), default=0)}


def _small(spark, d) -> dict[str, Hypergraph]:
    return {name: W.HYPERGRAPHS[name](spark, d).materialised("input") for name in ("w6", "w7")}


#: Small levels and few repetitions: instances of hundreds of nodes must show a hierarchy.
QUICK = {"coarse_per_block": 16, "runs": (2, 4, True)}


def _presets(spark, d) -> tuple[DataFrame, DataFrame]:
    return sweep(_small(spark, d), list(PRESETS), [2, 8], [1, 2], changes=QUICK)


def x_cfg(spark, d) -> DataFrame:
    """Quality and time of the five presets on two workloads, k = 2 and 8, two seeds: harmonic mean ratios to the best and who is on the front."""
    runs, _ = _presets(spark, d)
    names = spark.createDataFrame(list(enumerate(PRESETS)), "algo long, name string")
    return evaluate.pareto(runs).join(F.broadcast(names), "algo")


def x_eff(spark, d) -> DataFrame:
    """Effectiveness of default against quality on equal time."""
    return evaluate.effectiveness(_presets(spark, d)[0].withColumn("seconds", F.ceil(F.col("seconds") * 1000)), 1, 3)


def x_comp(spark, d) -> DataFrame:
    """Median share of each step in the running time."""
    _, phases = _presets(spark, d)
    return evaluate.component_shares(phases.filter("algo = 1").select("instance", "phase", "seconds"))


def x_seq(spark, d) -> DataFrame:
    """Performance profiles of default and the stand-ins of the compared systems."""
    names = ["default", "rb_matching", "kway_matching", "kway_eco", "rb_cluster", "lp_fast", "fm_local_only", "n_level"]
    runs, _ = sweep(_small(spark, d), names, [2, 8], [1], changes=QUICK)
    return evaluate.profile(runs, [1.0, 1.05, 1.1, 1.5]).join(F.broadcast(spark.createDataFrame(list(enumerate(names)), "algo long, name string")), "algo")


def x_scal(spark, d) -> DataFrame:
    return threads(W.shared_lines(spark, d).materialised("input"), 8, [1, 2, 4], changes=QUICK)


def x_lim(spark, d) -> DataFrame:
    """Limits: many blocks, and next to no imbalance; said as it is where no balanced partition was found."""
    h, rows = W.event_windows(spark, d).materialised("input"), []
    for k, eps in ((64, 0.03), (8, 0.001), (8, 0.0)):
        m = partition(h, k, eps, config=replace(PRESETS["default"], **QUICK)).metrics.first()
        rows.append((k, eps, m["km1"], m["imbalance"], m["feasible"]))
    return spark.createDataFrame(rows, "k int, eps double, km1 long, imbalance double, feasible boolean")


def x_work(spark, d) -> DataFrame:
    """What one default run shuffles and spills."""
    h = W.shared_lines(spark, d)
    got = work_done(spark, lambda: partition(h, 8, EPS, config=replace(PRESETS["default"], **QUICK)).blocks.count())
    return spark.createDataFrame([tuple(got.values())], ", ".join(f"{k} long" for k in got))


for _f in (x_cfg, x_eff, x_comp, x_seq, x_scal, x_lim):
    QUERIES[_f.__name__] = _f
QUERIES["q23_work_w7"] = x_work


#: Pins of a connected part up to which a run is one task: with 3.6 million it takes 1.1 to 2.4 GB there, as tables many times as long.
RUN_PINS = 4_000_000


def values(h: Hypergraph, names: list[str], k: int, eps: float, seed: int, changes: dict, task_pins: int | None = None, lists: DataFrame | None = None) -> dict[str, int]:
    """Connectivity of one run of each algorithm on the whole of ``h``.

    An input of at most ``TASK_PINS`` pins is a task a run. Of a larger one, components are put whole into blocks as far as they balance, and the runs share out the rest, part by
    part: in tasks up to ``RUN_PINS`` pins, else as tables (``task_pins`` stands for both bounds). All nets count.
    """
    spark = h.pins.sparkSession
    split, most = (initial.TASK_PINS, RUN_PINS) if task_pins is None else (task_pins, task_pins)
    if h.pins.count() <= split:
        parts = [(h, k, eps)]
    else:
        parts = components.parts(h, k, eps, lists)
        parts = [(h, k, eps)] if parts is None else parts
    found = dict.fromkeys(names, 0)

    def in_tasks(some):
        if len(some) == 1:
            # all tasks have the same part, which is sent once
            ran = initial.tasks(spark, lambda held, n: run_one(held[0], (n, *held[1:], seed, changes)), names, some[0])
            for name, r in zip(names, ran, strict=True):
                found[name] += r[1]
            return
        # a part goes with its tasks, which need no other
        args = [(n, *x) for x in some for n in names]
        for (name, *_), r in zip(args, initial.tasks(spark, lambda _, x: run_one(x[1], (x[0], *x[2:], seed, changes)), args), strict=True):
            found[name] += r[1]

    held, size = [], 0
    for part, blocks, e in parts:
        pins = part.pins.count()
        if pins > most:
            for name in names:
                found[name] += partition(part, blocks, e, seed=seed, config=replace(CONFIGS[name], **changes)).metrics.first()["km1"]
            continue
        if held and size + pins > 1.5 * split:
            in_tasks(held)
            held, size = [], 0
        held.append((Csr.of(initial.gather(part)), blocks, e))
        size += pins
    if held:
        in_tasks(held)
    return found


def x_facts(spark, d) -> DataFrame:
    """What the comparison of presets must show: better methods win. One row, so that SQL can say it."""
    lists = truncate_lineage(W.order_part_lists(spark, d), "lists")
    pins, one = from_pinlists(lists), F.lit(1).cast("long").alias("weight")
    h = Hypergraph(truncate_lineage(pins.select("node").distinct().select("node", one), "nodes"), lists.select("net", one, F.size("nodes").alias("size")), pins)
    value = values(h, ["default", "no_fm", "speed_det"], 8, EPS, 1, {"runs": (1, 1, False)}, lists=lists)
    # of blocks dealt by id modulo 8
    floor = lists.agg(F.coalesce(F.sum(F.size(F.array_distinct(F.transform("nodes", lambda x: F.pmod(x, F.lit(8))))) - 1), F.lit(0)).cast("long").alias("floor"))
    return floor.select("floor", F.lit(value["default"] <= value["no_fm"]).alias("fm_helps"), (F.lit(value["default"]) < F.col("floor")).alias("default_below_floor"), (F.lit(value["speed_det"]) < F.col("floor")).alias("det_below_floor"))


QUERIES["x_nofm_facts"] = x_facts
SQL["x_nofm_facts"] = over("w1", "SELECT (SELECT CAST(sum(n) AS BIGINT) FROM (SELECT count(DISTINCT node % 8) - 1 AS n FROM pins GROUP BY net)) AS floor, TRUE AS fm_helps, TRUE AS default_below_floor, TRUE AS det_below_floor")
QUERIES["q22_levels_w7"] = lambda spark, d: levels(spark, W.shared_lines(spark, d))


def x_graph(spark, d) -> DataFrame:
    """(graph_opt, cut, refinement seconds) of one run on the co-purchase graph with and without the structures for graphs."""
    from ..operators import graphs

    edges, rows = truncate_lineage(W.co_purchases(spark, d), "edges"), []
    for opt in (True, False):
        got = graphs.partition(edges, 8, EPS, graph_opt=opt, runs=(1, 1, False))
        rows.append((opt, got.metrics.first()["cut"], sum(r["seconds"] for r in got.log if r["phase"] in ("lp", "fm"))))
    return spark.createDataFrame(rows, "graph_opt boolean, cut long, seconds double")


def z07_graph(spark, d) -> DataFrame:
    """The structures for graphs change the time, not the result: one row, so that SQL can say it."""
    from ..operators import graphs

    edges = truncate_lineage(W.nation_trade(spark, d), "edges")
    a, b = (graphs.partition(edges, 4, 0.2, graph_opt=opt, runs=(2, 2, False)).blocks for opt in (True, False))
    both = a.join(b.select("node", F.col("block").alias("other")), "node")
    return both.agg(F.count("*").alias("nodes"), F.bool_and(F.col("block") == F.col("other")).alias("same"))


QUERIES["x_graph_w13"] = x_graph
QUERIES["z07_graph_w16"] = z07_graph
SQL["z07_graph_w16"] = "SELECT count(DISTINCT n) AS nodes, TRUE AS same FROM (SELECT c_nationkey AS n FROM customer JOIN orders ON c_custkey = o_custkey JOIN lineitem ON l_orderkey = o_orderkey JOIN supplier ON l_suppkey = s_suppkey WHERE c_nationkey <> s_nationkey UNION ALL SELECT s_nationkey FROM supplier JOIN lineitem ON l_suppkey = s_suppkey JOIN orders ON l_orderkey = o_orderkey JOIN customer ON c_custkey = o_custkey WHERE c_nationkey <> s_nationkey)"
