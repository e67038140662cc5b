"""Distributed operators on small fixtures against the kernels and hand-made results."""

import random
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from hgpart.functions import kernels
from hgpart.functions.arrays import Csr
from hgpart.model import build, from_pinlists, induced, reference_partition, to_pinlists
from hgpart.operators import coarsen, community, contract, gains, graphs, initial, joins, metrics, nlevel, prefix, refine
from hgpart.plans import baselines, multilevel
from hgpart.sources import formats, store, workloads


def hypergraph(spark, nets, weights=None, node_weights=None):
    pins = spark.createDataFrame([(e, v) for e, vs in enumerate(nets) for v in vs] or [], "net long, node long")
    w = spark.createDataFrame([(e, x) for e, x in enumerate(weights or [1] * len(nets))], "net long, weight long")
    nodes = None if node_weights is None else spark.createDataFrame(list(enumerate(node_weights)), "node long, weight long")
    return build(pins, nodes, w)


def part(spark, blocks):
    return spark.createDataFrame(list(enumerate(blocks)), "node long, block int")


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_ring(spark):
    h, p = hypergraph(spark, [[0, 1], [1, 2], [2, 3], [0, 3]]), part(spark, [0, 0, 1, 1])
    assert metrics.objectives_df(h, p).first().asDict() == {"cut": 2, "km1": 2, "soed": 4, "cut_nets": 2}
    assert rows(metrics.quotient_graph(h, p)) == [(0, 1, 2, 2)] and len(rows(metrics.boundary_nodes(h, p))) == 4
    one = hypergraph(spark, [[0, 1, 2]])
    assert metrics.objectives_df(one, part(spark, [0, 1, 2])).first()[:3] == (1, 2, 3)
    assert metrics.max_block_weight(10, 3, 0.25) == 5 and metrics.is_balanced(h, p, 2, 0.0)


def test_build_and_induced(spark):
    pins = spark.createDataFrame([(0, 1), (0, 1), (None, 2), (3, None), (0, 2)], "net long, node long")
    h = build(pins)
    assert rows(h.nets) == [(0, 1, 2)] and rows(h.pins) == [(0, 1), (0, 2)]
    assert rows(from_pinlists(to_pinlists(h.pins))) == rows(h.pins)
    empty = build(pins.limit(0))
    assert metrics.objectives_df(empty, part(spark, [0])).first()["km1"] == 0 and rows(empty.nets) == []
    assert rows(induced(h, spark.createDataFrame([(1,)], "node long")).nets) == []


def random_case(seed, n=14, m=24, k=3):
    rng = random.Random(seed)
    nets = [rng.sample(range(n), rng.randint(2, 4)) for _ in range(m)]
    return rng, nets, [rng.randint(1, 4) for _ in nets], [rng.randrange(k) for _ in range(n)]


@pytest.mark.parametrize("seed", range(4))
def test_gains_and_sequences(spark, seed):
    rng, nets, w, blocks = random_case(seed)
    h, p, k = hypergraph(spark, nets, w), part(spark, blocks), 3
    g = kernels.Local(nets, w, [1] * 14)
    state = kernels.State(g, blocks, k)
    for v, b, x in rows(gains.gains(h, p)):
        assert x == state.gain(v, b)
    order = rng.sample(range(14), 8)
    targets = [(v, (blocks[v] + rng.randint(1, 2)) % 3) for v in order]
    moves = spark.createDataFrame([(i, v, blocks[v], t) for i, (v, t) in enumerate(targets)], "idx long, node long, src int, dst int")
    exact = [r["gain"] for r in gains.recalculate(h, p, moves).orderBy("idx").collect()]
    assert exact == kernels.recalc_sequential(g, blocks, targets)
    benefit, present = gains.gain_table(h, p)
    b2, p2 = gains.apply_delta(benefit, present, h, p, moves)
    fresh = gains.gain_table(h, gains.moved(p, moves))
    assert rows(b2) == rows(fresh[0]) and rows(p2) == rows(fresh[1])
    # best prefix by enumeration
    l_max, weight, total, best = 6, g.weights(blocks, k), 0, (0, -1)
    first = list(weight)
    for i, (v, t) in enumerate(targets):
        weight[blocks[v]] -= 1
        weight[t] += 1
        total += exact[i]
        if total > best[0] and all(x <= max(l_max, f) for x, f in zip(weight, first)):
            best = (total, i)
    got = gains.best_prefix(gains.recalculate(h, p, moves), moves, h, p, k, l_max).first()
    assert (got["gain"], got["idx"]) == best


def test_joining_paths_and_cycles(spark):
    t = spark.createDataFrame([(0, 1), (1, 2), (3, 4), (4, 5), (5, 3), (6, 3)], "node long, target long")
    got = dict(rows(coarsen.resolve_joins(t)))
    assert {got[v] for v in (0, 1, 2)} == {2} and {got[v] for v in (3, 4, 5, 6)} == {4}
    for mode in ("star", "postprocess"):
        x = dict(rows(coarsen.resolve_joins(t, mode)))
        assert all(x.get(r, r) == r for r in x.values())
    joins_ = spark.createDataFrame([(0, 0), (1, 0), (2, 0), (3, 0)], "node long, rep long")
    nodes = spark.createDataFrame([(0, 1), (1, 1), (2, 2), (3, 3)], "node long, weight long")
    assert rows(coarsen.cap(joins_, nodes, 5).distinct()) == [(0, 0), (1, 0), (2, 0)]
    assert len(rows(coarsen.cap(joins_, nodes, 7))) == 4
    limited = coarsen.limit_round(joins_, spark.createDataFrame([(1, 5), (2, 9), (3, 1)], "node long, rating long"), 4, 1.4)
    assert rows(limited) == [(0, 0), (2, 0)]
    clustered = spark.createDataFrame([(2, 9), (9, 9)], "node long, rep long")
    assert dict(rows(coarsen.resolve_joins(t, clustered=clustered)))[0] == 9


def test_contraction_keeps_objectives(spark):
    _, nets, w, blocks = random_case(11, n=30, m=60)
    h = hypergraph(spark, nets, w)
    clusters = coarsen.cluster(h, 4, seed=3)
    assert rows(clusters.join(clusters.select(F.col("node").alias("rep"), F.col("rep").alias("top")), "rep").filter("top <> rep")) == []
    coarse, mapping, kept = contract.contract(h, clusters)
    assert metrics.total_weight(coarse) == metrics.total_weight(h) and coarse.nodes.agg(F.max("weight")).first()[0] <= 4
    p = reference_partition(coarse, 3)
    assert metrics.km1(coarse, p) == metrics.km1(h, contract.project(p, mapping))
    assert kept.count() >= coarse.nets.count()
    # equal sums of squares, different pins
    twin = hypergraph(spark, [[1, 8], [4, 7], [8, 1], [2, 3]], [1, 1, 2, 1])
    for f in ("sumsq", "xx", None):
        merged, names = contract.merge_identical(twin, f)
        assert rows(merged.nets) == [(0, 3, 2), (1, 1, 2), (3, 1, 2)] and rows(names) == [(0, 0), (1, 1), (2, 0), (3, 3)]


def test_prefix_sums(spark):
    df = spark.range(0, 1000, 1, 7).select((F.col("id") * 37 % 1009).alias("k"), (F.col("id") % 5).alias("x"))
    got = prefix.running_sum(df, "k", "x").orderBy("k").collect()
    total = 0
    for r in got:
        total += r["x"]
        assert r["running"] == total
    assert prefix.running_sum(df.limit(0), "k", "x").collect() == []
    assert rows(prefix.dense_ids(spark.createDataFrame([("b",), ("a",), ("b",)], "k string"), "k")) == [("a", 0), ("b", 1)]


def test_communities_find_planted_blocks(spark):
    h = workloads.planted(spark, 60, 500, 3, inside=0.95, seed=2)
    found = community.louvain(h, max_rounds=3, subrounds=2, max_levels=4)
    e = community.weighted_edges(h)
    every = found.select((F.col("node") * 2).alias("node"), "community").collect()
    names = {r["node"] // 2: r["community"] for r in every}
    groups = {b: {names[v] for v in names if v % 3 == b} for b in range(3)}
    pure = sum(max(sum(names[v] == c for v in names if v % 3 == b) for c in groups[b]) for b in range(3))
    assert pure >= 0.8 * len(names)
    for model in ("uniform", "inverse_size", "degree"):
        assert community.weighted_edges(h, model).count() == h.pins.count()
    assert -0.5 <= community.modularity(e, community.both_ways(e).select(F.col("src").alias("node"), (F.col("src") % 2).alias("community")).distinct()) <= 1


def test_refinement_improves_and_balances(spark):
    h = workloads.planted(spark, 120, 500, 4, inside=0.9, seed=1).materialised()
    p = baselines.random_blocks(h, 4)
    start = metrics.km1(h, p)
    for f, rounds in ((refine.lp, 1), (refine.deterministic_lp, 1), (refine.fm, 1), (refine.flows, 1)):
        q, log = f(h, p, 4, 0.1, rounds)
        after = metrics.km1(h, q)
        assert (after < start if f in (refine.fm, refine.flows) else after <= start) and log, f.__name__
        assert metrics.is_balanced(h, q, 4, 0.1) and q.count() == 120, f.__name__


def test_swaps_follow_the_walk(spark):
    rng = random.Random(3)
    for _ in range(5):
        n = 16
        node_w = [rng.randint(1, 4) for _ in range(n)]
        side = [rng.randrange(2) for _ in range(n)]
        gain = [rng.randint(1, 9) for _ in range(n)]
        h = hypergraph(spark, [[0, 1]], node_weights=node_w)
        wishes = spark.createDataFrame([(v, side[v], 1 - side[v], gain[v]) for v in range(n)], "node long, src int, dst int, gain long")
        slack = spark.createDataFrame([(0, 3), (1, 2)], "block int, room long")
        order = [sorted((v for v in range(n) if side[v] == b), key=lambda v: (-gain[v], v)) for b in (0, 1)]
        i, j = kernels.swap_prefix_walk([node_w[v] for v in order[0]], [node_w[v] for v in order[1]], 2, 3)
        assert {r["node"] for r in refine.swaps(wishes, h, slack).collect()} == {*order[0][:i], *order[1][:j]}


def test_deterministic_preset_ignores_the_layout(spark):
    h = workloads.planted(spark, 90, 300, 3, seed=4)
    config = replace(multilevel.PRESETS["speed_det"], task_pins=200, coarse_per_block=10, communities=False, superstep_rounds=1, runs=(1, 1, False))
    results = []
    for n, aqe in ((3, "true"), (7, "false")):
        spark.conf.set("spark.sql.adaptive.enabled", aqe)
        q = h.map(lambda df, n=n: df.repartition(n))
        results.append(rows(multilevel.partition(q, 3, 0.1, "speed_det", config=config).blocks.select("node", "block")))
    spark.conf.set("spark.sql.adaptive.enabled", "true")
    assert results[0] == results[1]


def test_portfolios_ignore_the_number_of_tasks(spark):
    a = initial.gather(workloads.planted(spark, 60, 200, 4, seed=8))
    g = Csr.of(a)
    one, three = (initial.recursive(spark, g, 4, 0.1, runs=(2, 6, True), width=w) for w in (1, 3))
    assert (one == three).all() and g.weights(one, 4).max() <= 17
    part, log = initial.one_run(spark, a, 4, 0.1, replace(multilevel.PRESETS["default"], coarse_per_block=5, runs=(1, 1, False)))
    assert {r["phase"] for r in log} >= {"level", "communities", "coarsening", "initial", "lp", "fm"}
    assert g.objective(part, 4) <= g.objective(np.arange(60) % 4, 4) + 5


def test_initial_partition_of_too_many_pins(spark):
    h = workloads.planted(spark, 60, 200, 4, seed=8)
    some = initial.heaviest_nets(h, 300)
    assert 0 < some.pins.count() <= 400 and some.nodes.count() == h.nodes.count()
    assert len(initial.gather(h, limit=300)["net"]) <= 400


def test_presets_beat_floors(spark):
    h = workloads.planted(spark, 120, 500, 4, inside=0.9, seed=5).materialised()
    floor = metrics.km1(h, baselines.hashed(h, 4))
    for preset in multilevel.PRESETS:
        got = multilevel.partition(h, 4, 0.05, config=replace(multilevel.PRESETS[preset], coarse_per_block=10, runs=(2, 2, False)))
        m = got.metrics.first()
        assert m["feasible"] and m["km1"] < 0.6 * floor, preset
        assert rows(got.blocks.select("node").distinct()) == rows(h.nodes.select("node"))
    better = multilevel.vcycle(h, baselines.random_blocks(h, 4), 4, 0.05)
    assert better.metrics.first()["km1"] < floor
    wide = multilevel.partition(h, 4, 0.05, config=multilevel.Config(scheme="recursive", communities=False, runs=(1, 1, False)))
    assert wide.metrics.first()["km1"] < floor


def test_stand_ins_and_floors(spark):
    h = workloads.planted(spark, 60, 200, 3, seed=6).materialised()
    for name in ("rb_matching", "kway_strong", "n_level"):
        p = baselines.stand_in(h, 3, 0.1, name)
        assert p.count() == 60 and metrics.is_balanced(h, p, 3, 0.1), name
    for p in (baselines.round_robin(h, 3), baselines.range_blocks(h, 3), baselines.random_blocks(h, 3), baselines.flat_lp(h, 3, 0.1), baselines.bfs_grow(h, 3, 0.1)):
        assert p.count() == 60 and {r["block"] for r in p.collect()} <= {0, 1, 2}
    tiny = hypergraph(spark, [[0, 1, 2], [3, 4, 5], [2, 3]])
    assert metrics.km1(tiny, baselines.exact(tiny, 2, 0.0)) == 1
    table = spark.createDataFrame([(1, "b"), (2, "a"), (3, None)], "id long, x string")
    assert rows(baselines.by_attribute(table, "id", "x")) == [(1, 1), (2, 0)]


def test_extreme_inputs(spark):
    single = hypergraph(spark, [[0, 1]], node_weights=[1, 1, 1])
    for k in (1, 2, 5):
        got = multilevel.partition(single, k, 0.03)
        assert got.blocks.count() == 3 and got.metrics.first()["feasible"]


def test_nlevel_tables(spark):
    h = workloads.planted(spark, 80, 200, 2, seed=7)
    forest, rep = nlevel.coarsen_forest(h, 2, per_block=10, max_passes=3)
    f = {r["node"]: (r["parent"], r["tau"]) for r in forest.collect()}
    for v, (u, tau) in f.items():
        assert v != u and (u not in f or f[u][1] > tau)
    b = {r["node"]: r["batch"] for r in nlevel.batches(forest, 7).collect()}
    assert set(b) == set(f) and all(b[v] > b[u] for v, (u, _) in f.items() if u in b)
    pins_v = nlevel.versioned_pins(h, forest)
    for tau in (0, 2):
        root = {}
        for v in [r["node"] for r in h.nodes.collect()]:
            u = v
            while u in f and f[u][1] < tau:
                u = f[u][0]
            root[v] = u
        assert rows(nlevel.active(pins_v, tau)) == sorted({(e, root[v]) for e, v in rows(h.pins.select("net", "node"))})


def test_graph_twins(spark):
    rng = random.Random(1)
    edges = {tuple(sorted(rng.sample(range(12), 2))): rng.randint(1, 5) for _ in range(30)}
    e = spark.createDataFrame([(a, b, w) for (a, b), w in edges.items()], "src long, dst long, weight long")
    h, p = graphs.to_hypergraph(e), part(spark, [v % 3 for v in range(12)])
    assert rows(graphs.from_hypergraph(h)) == rows(e) and graphs.edge_cut(e, p).first()["cut"] == metrics.km1(h, p)
    assert rows(graphs.gains(e, p)) == rows(gains.gains(h, p))
    moves = spark.createDataFrame([(i, v, v % 3, (v + 1) % 3) for i, v in enumerate(sorted({x for ab in edges for x in ab})[::2])], "idx long, node long, src int, dst int")
    assert rows(graphs.attributed(e, p, moves)) == rows(gains.recalculate(h, p, moves))
    assert rows(graphs.rate(e)) == sorted([(a, b, w) for (a, b), w in edges.items()] + [(b, a, w) for (a, b), w in edges.items()])
    assert graphs.partition(e, 2, 0.2).metrics.first()["feasible"]
    assert graphs.neighbours(e).count() == len({x for ab in edges for x in ab})


def test_joins(spark):
    a = spark.createDataFrame([(1, 5, "x"), (1, 1, "y"), (2, 9, "z")], "k long, t long, name string")
    b = spark.createDataFrame([(1, 2, 20), (1, 5, 50), (1, 5, 51), (2, 10, 7)], "k long, t long, v long")
    assert rows(joins.asof(a, b, "t", "k", "v").select("name", "v").na.fill(-1)) == [("x", 51), ("y", -1), ("z", -1)]


def test_formats_round_trip(spark, tmp_path):
    h = hypergraph(spark, [[0, 1, 2], [2, 3], [1]], [3, 1, 2], [1, 2, 3, 4])
    formats.write_hgr(h, str(tmp_path / "h"))
    back = formats.read_hgr(spark, str(tmp_path / "h"))
    assert rows(back.pins) == rows(h.pins) and rows(back.nodes) == rows(h.nodes) and rows(back.nets.select("net", "weight")) == rows(h.nets.select("net", "weight"))
    (tmp_path / "g.graph").write_text("% c\n3 2 1\n2 5\n1 5 3 7\n2 7\n")
    assert rows(formats.read_graph(spark, str(tmp_path / "g.graph"))) == [(0, 1, 5), (1, 2, 7)]
    (tmp_path / "m.mtx").write_text("%%MatrixMarket\n2 3 3\n1 1 4.5\n1 3 1\n2 2 1\n")
    assert rows(formats.read_mtx(spark, str(tmp_path / "m.mtx")).pins) == [(0, 0), (0, 2), (1, 1)]
    (tmp_path / "f.cnf").write_text("c x\np cnf 3 2\n1 -2 0\n2 3 0\n")
    assert rows(formats.read_cnf(spark, str(tmp_path / "f.cnf")).pins) == [(0, 0), (0, 1), (1, 1), (1, 2)]
    assert rows(formats.read_cnf(spark, str(tmp_path / "f.cnf"), "literal").pins) == [(0, 0), (0, 3), (1, 2), (1, 4)]
    assert rows(formats.read_cnf(spark, str(tmp_path / "f.cnf"), "dual").pins) == [(0, 0), (1, 0), (1, 1), (2, 1)]
    store.write_level(h, str(tmp_path / "levels"), 2)
    assert rows(store.read_level(spark, str(tmp_path / "levels"), 2).pins) == rows(h.pins)
    store.write_blocks(part(spark, [3, 1, 2]), str(tmp_path / "blocks"))
    assert [x for f in sorted((tmp_path / "blocks").glob("part*")) for x in f.read_text().split()] == ["3", "1", "2"]
    store.write_partition(part(spark, [3, 1, 3]), str(tmp_path / "parts"))
    assert spark.read.parquet(str(tmp_path / "parts")).filter("block = 3").count() == 2
