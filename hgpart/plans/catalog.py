"""The registered queries of the partitioning engine, with SQL where SQL can say the same."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .. import model
from ..functions import kernels
from ..model import Hypergraph, reference_partition
from ..operators import coarsen, community, contract, gains, graphs, initial, joins, metrics, nlevel, prefix, refine
from ..sources import workloads as W
from ..sources.store import truncate_lineage
from . import evaluate

K, EPS = 8, 0.03
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}
#: Names of the queries that run a whole partitioner.
WHOLE: set[str] = set()


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return add


# -- SQL of the workloads -----------------------------------------------------------------------

PINS_SQL = {
    "w1": "SELECT DISTINCT l_orderkey AS net, l_partkey AS node FROM lineitem",
    "w3d": "SELECT DISTINCT l_partkey AS net, l_orderkey AS node FROM lineitem",
    "w3l": "SELECT DISTINCT l_orderkey AS net, 2 * l_partkey + CASE WHEN l_returnflag = 'R' THEN 1 ELSE 0 END AS node FROM lineitem",
    "w2s": "SELECT DISTINCT l_suppkey AS net, l_partkey AS node FROM lineitem",
    "w4": "SELECT DISTINCT o_custkey AS net, l_partkey AS node FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "w4t": "SELECT o_orderkey AS net, 4 * o_custkey AS node FROM orders UNION SELECT l_orderkey, 4 * l_partkey + 1 FROM lineitem UNION SELECT l_orderkey, 4 * l_suppkey + 2 FROM lineitem",
    "w6": "SELECT DISTINCT CAST(floor(epoch(ts) / 3600) AS BIGINT) * 5 + list_position(['click', 'error', 'purchase', 'signup', 'view'], event_type) - 1 AS net, user_id AS node FROM events",
    "w2": r"""SELECT dense_rank() OVER (ORDER BY token) - 1 AS net, node FROM (
        SELECT token, node, count(*) OVER (PARTITION BY token) AS n FROM (
            SELECT DISTINCT doc_id AS node, unnest(regexp_split_to_array(lower(text), '[ \t\r\n]+')) AS token FROM documents) WHERE length(token) >= 4) WHERE n BETWEEN 2 AND 50""",
    "w5": """SELECT dense_rank() OVER (ORDER BY href) - 1 AS net, node FROM (SELECT DISTINCT page_id AS node, unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) AS href FROM pages)""",
    "w7": r"""SELECT dense_rank() OVER (ORDER BY line) - 1 AS net, node FROM (
        SELECT line, node, count(*) OVER (PARTITION BY line) AS n FROM (
            SELECT DISTINCT doc_id AS node, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) >= 20) WHERE n > 1""",
    "w12": """SELECT dense_rank() OVER (ORDER BY token) - 1 AS net, node FROM (
        SELECT token, node, count(*) OVER (PARTITION BY token) AS n FROM (
            SELECT DISTINCT conv_id AS node, unnest(string_split(lower(text), ' ')) AS token FROM conversations) WHERE token <> '') WHERE n > 1""",
}
PINS_SQL["w2t"] = f"SELECT node AS net, net AS node FROM ({PINS_SQL['w2']})"


def over(w: str, body: str, k: int = K) -> str:
    """``body`` over pins, nodes, nets and the reference partition of a workload with unit weights."""
    return f"""WITH RECURSIVE pins AS MATERIALIZED ({PINS_SQL[w]}),
        nodes AS (SELECT DISTINCT node FROM pins), nets AS (SELECT net, count(*) AS size FROM pins GROUP BY net),
        part AS (SELECT node, CAST((node * 7919 + 13) % {k} AS INTEGER) AS block FROM nodes),
        phi AS (SELECT net, block, count(*) AS cnt FROM pins JOIN part USING (node) GROUP BY net, block),
        lam AS (SELECT net, count(*) AS la FROM phi GROUP BY net)
        {body}"""


def w1(spark, sf_dir) -> tuple[Hypergraph, DataFrame]:
    h = W.order_parts(spark, sf_dir)
    return h, reference_partition(h, K)


def reference_moves(h: Hypergraph, p: DataFrame) -> DataFrame:
    """A fixed sequence: nodes with node % 3 = 0 in ascending order, each to the block after its own."""
    x = p.filter("node % 3 = 0").withColumn("one", F.lit(1))
    return prefix.running_sum(x, "node", "one", "idx", exclusive=True).select("idx", "node", F.col("block").alias("src"), F.pmod(F.col("block") + 1, F.lit(K)).cast("int").alias("dst"))


MOVES = "moves AS (SELECT row_number() OVER (ORDER BY node) - 1 AS idx, node, block AS src, (block + 1) % 8 AS dst FROM part WHERE node % 3 = 0)"


# -- problem, objectives --------------------------------------------------------------------------


@query("m01_block_weights", over("w1", "SELECT block, CAST(count(*) AS BIGINT) AS weight, CAST(greatest(count(*) - floor(1.03 * ceil((SELECT count(*) FROM nodes) / 8.0) + 1e-9), 0) AS BIGINT) AS overload FROM part GROUP BY block"))
def _(spark, d):
    return metrics.block_weights(*w1(spark, d), K, EPS)


@query("m02_pin_counts", over("w1", "SELECT net, block, cnt FROM phi"))
def _(spark, d):
    return metrics.pin_counts(*w1(spark, d))


@query("m03_connectivity", over("w1", "SELECT net, CAST(count(*) AS INTEGER) AS \"lambda\", string_agg(block, ',' ORDER BY block) AS blocks FROM phi GROUP BY net"))
def _(spark, d):
    return metrics.connectivity(metrics.pin_counts(*w1(spark, d))).withColumn("blocks", F.array_join(F.transform("blocks", lambda b: b.cast("string")), ","))


@query("m03_bitset", over("w1", "SELECT net, CAST(count(*) AS INTEGER) AS \"lambda\", CAST(sum(1 << block) AS BIGINT) AS mask FROM phi GROUP BY net"))
def _(spark, d):
    return metrics.connectivity_bitset(metrics.pin_counts(*w1(spark, d)), K)


@query("m04_cut_nets", over("w1", "SELECT net FROM lam WHERE la > 1"))
def _(spark, d):
    return metrics.cut_nets(*w1(spark, d))


@query("m04_boundary", over("w1", "SELECT DISTINCT node FROM pins JOIN lam USING (net) WHERE la > 1"))
def _(spark, d):
    return metrics.boundary_nodes(*w1(spark, d))


@query("m05_quotient", over("w1", "SELECT a.block AS bi, b.block AS bj, CAST(count(*) AS BIGINT) AS weight, count(*) AS n FROM phi a JOIN phi b ON a.net = b.net AND a.block < b.block GROUP BY 1, 2"))
def _(spark, d):
    return metrics.quotient_graph(*w1(spark, d))


@query("m06_induced", over("w1", "SELECT net, CAST(1 AS BIGINT) AS weight, CAST(count(*) AS INTEGER) AS size FROM pins WHERE node % 2 = 0 GROUP BY net HAVING count(*) > 1"))
def _(spark, d):
    h, _p = w1(spark, d)
    return model.induced(h, h.nodes.filter("node % 2 = 0")).nets


@query("m07_bipartite", over("w1", "SELECT 2 * node AS src, 2 * net + 1 AS dst, CAST(1 AS BIGINT) AS weight FROM pins"))
def _(spark, d):
    return model.bipartite(w1(spark, d)[0])


@query("q01_cut", over("w1", "SELECT CAST(count(*) AS BIGINT) AS cut FROM lam WHERE la > 1"))
def _(spark, d):
    return metrics.objectives_df(*w1(spark, d)).select("cut")


for _w in ("w1", "w2", "w2t", "w2s", "w3d", "w3l", "w4", "w4t", "w5", "w6", "w7", "w12"):

    @query(f"q02_km1_{_w}", over(_w, "SELECT CAST(coalesce(sum(la - 1), 0) AS BIGINT) AS km1, CAST(coalesce(sum(CASE WHEN la > 1 THEN la END), 0) AS BIGINT) AS soed, CAST(count(*) FILTER (WHERE la > 1) AS BIGINT) AS cut FROM lam"))
    def _(spark, d, w=_w):
        h = W.HYPERGRAPHS[w](spark, d)
        return metrics.objectives_df(h, reference_partition(h, K)).select("km1", "soed", "cut")

    @query(f"q19_describe_{_w}", over(_w, """, deg AS (SELECT node, count(*) AS g FROM pins GROUP BY node)
        SELECT (SELECT count(*) FROM nodes) AS nodes, (SELECT count(*) FROM nodes) AS node_weight, (SELECT count(*) FROM nets) AS nets,
        (SELECT CAST(sum(size) AS BIGINT) FROM nets) AS pins, (SELECT quantile_cont(size, 0.5) FROM nets) AS median_size, (SELECT max(size) FROM nets) AS max_size,
        (SELECT quantile_cont(g, 0.5) FROM deg) AS median_degree, (SELECT max(g) FROM deg) AS max_degree"""))
    def _(spark, d, w=_w):
        return metrics.describe(W.HYPERGRAPHS[w](spark, d))


QUERIES["q02_km1"], SQL["q02_km1"] = (lambda spark, d: metrics.objectives_df(*w1(spark, d)).select("km1")), over("w1", "SELECT CAST(sum(la - 1) AS BIGINT) AS km1 FROM lam")


@query("q03_soed", over("w1", "SELECT CAST(sum(la) AS BIGINT) AS soed FROM lam WHERE la > 1"))
def _(spark, d):
    return metrics.objectives_df(*w1(spark, d)).select("soed")


@query("q04_imbalance", over("w1", "SELECT round(max(n) / ceil((SELECT count(*) FROM nodes) / 8.0) - 1, 9) AS imbalance, round(max(n) / ceil((SELECT count(*) FROM nodes) / 8.0) - 1, 9) <= 0.03 + 1e-9 AS feasible FROM (SELECT count(*) AS n FROM part GROUP BY block)"))
def _(spark, d):
    return metrics.imbalance_df(*w1(spark, d), K, EPS)


@query("q04_weighted", """WITH pins AS (SELECT DISTINCT l_orderkey AS net, l_partkey AS node FROM lineitem), nodes AS (SELECT p_partkey AS node, p_size + 1 AS w FROM part WHERE p_partkey IN (SELECT node FROM pins)),
        b AS (SELECT (node * 7919 + 13) % 8 AS block, sum(w) AS n FROM nodes GROUP BY 1), nw AS (SELECT l_orderkey AS net, count(*) AS w FROM lineitem GROUP BY 1),
        lam AS (SELECT net, count(DISTINCT (node * 7919 + 13) % 8) AS la FROM pins GROUP BY net)
        SELECT CAST(sum((la - 1) * w) AS BIGINT) AS km1, round((SELECT max(n) FROM b) / ceil((SELECT sum(n) FROM b) / 8.0) - 1, 9) AS imbalance FROM lam JOIN nw USING (net)""")
def _(spark, d):
    h = W.weighted_order_parts(spark, d)
    return metrics.report(h, reference_partition(h, K), K, EPS).select("km1", "imbalance")


@query("q21_work", over("w1", "SELECT CAST(sum(size * least(size, 8)) AS BIGINT) AS gain_updates, CAST(sum(2 * size + 1) AS BIGINT) AS flow_edges, 2 * count(*) AS flow_net_nodes FROM nets"))
def _(spark, d):
    return metrics.work_bound(w1(spark, d)[0], K)


# -- coarsening -----------------------------------------------------------------------------------

RATING = "rating AS (SELECT a.node, b.node AS rep, CAST(sum(1048576 // (size - 1)) AS BIGINT) AS rating FROM pins a JOIN pins b ON a.net = b.net AND a.node <> b.node JOIN nets n ON n.net = a.net WHERE size >= 2 GROUP BY 1, 2)"
TARGET = "target AS (SELECT node, rep AS target, rating FROM (SELECT *, row_number() OVER (PARTITION BY node ORDER BY rating DESC, rep) AS r FROM rating) WHERE r = 1)"


@query("c01_rating", over("w1", f", {RATING} SELECT node, rep, rating FROM rating"))
def _(spark, d):
    return coarsen.rate(w1(spark, d)[0])


@query("c02_best_target", over("w1", f", {RATING}, {TARGET} SELECT node, target, rating FROM target"))
def _(spark, d):
    return coarsen.best_target(coarsen.rate(w1(spark, d)[0]), tie="min_id")


@query("c04_join_paths", over("w1", f""", {RATING}, target AS MATERIALIZED (SELECT node, rep AS target FROM (SELECT *, row_number() OVER (PARTITION BY node ORDER BY rating DESC, rep) AS r FROM rating) WHERE r = 1),
        walk(node, pos, step) AS (SELECT node, target, 1 FROM target UNION ALL SELECT w.node, t.target, step + 1 FROM walk w JOIN target t ON t.node = w.pos WHERE step < 64),
        lost AS (SELECT node, pos FROM walk WHERE step = 64),
        ring(head, pos, low, step) AS (SELECT DISTINCT pos, pos, pos, 0 FROM lost UNION ALL SELECT head, t.target, least(low, t.target), step + 1 FROM ring JOIN target t ON t.node = ring.pos WHERE step < 64),
        root AS (SELECT head, min(low) AS low FROM ring GROUP BY head),
        fin AS (SELECT l.node, t.target AS rep FROM lost l JOIN root r ON r.head = l.pos JOIN target t ON t.node = r.low)
        SELECT node, rep FROM fin"""))
def _(spark, d):
    h, _p = w1(spark, d)
    t = truncate_lineage(coarsen.best_target(coarsen.rate(h), tie="min_id"), "targets")
    return coarsen.resolve_joins(t).select("node", "rep")


@query("c04b_star", over("w1", f""", {RATING}, {TARGET}, c AS (SELECT node, ((node * 7919 + 13) // 16) % 2 = 0 AS coin FROM nodes),
        x AS (SELECT t.node, t.target, b.node IS NOT NULL AS mutual FROM target t LEFT JOIN target b ON b.node = t.target AND b.target = t.node),
        j AS (SELECT x.node, x.target FROM x JOIN c a ON a.node = x.node JOIN c b ON b.node = x.target WHERE CASE WHEN mutual THEN x.node > x.target ELSE a.coin AND NOT b.coin END),
        k AS (SELECT node, target FROM j WHERE target NOT IN (SELECT node FROM j)) SELECT node, target AS rep FROM k UNION ALL SELECT DISTINCT target, target FROM k"""))
def _(spark, d):
    h, _p = w1(spark, d)
    return coarsen.resolve_joins(coarsen.best_target(coarsen.rate(h), tie="min_id"), "star")


@query("c04c_postprocess", over("w1", f""", {RATING}, {TARGET}, j AS (SELECT a.node, a.target FROM target a LEFT JOIN target b ON b.node = a.target WHERE b.node IS NULL OR (b.target = a.node AND a.node > a.target))
        SELECT node, target AS rep FROM j UNION ALL SELECT DISTINCT target, target FROM j"""))
def _(spark, d):
    h, _p = w1(spark, d)
    return coarsen.resolve_joins(truncate_lineage(coarsen.best_target(coarsen.rate(h), tie="min_id"), "targets"), "postprocess")


@query("c05_cap", over("w1", """, j AS (SELECT node, node % 97 AS rep FROM nodes WHERE node % 97 IN (SELECT node FROM nodes)), r AS (SELECT node, rep, row_number() OVER (PARTITION BY rep ORDER BY node) AS n FROM j WHERE node <> rep)
        SELECT node, rep FROM r WHERE n + 1 <= 12 UNION SELECT DISTINCT rep, rep FROM r"""))
def _(spark, d):
    h, _p = w1(spark, d)
    j = h.nodes.select("node", (F.col("node") % 97).alias("rep")).join(h.nodes.select(F.col("node").alias("rep")), "rep", "left_semi").select("node", "rep")
    return coarsen.cap(j, h.nodes, 12).distinct()


@query("c08_rating_in_community", over("w1", """, ok AS (SELECT a.node, b.node AS rep, CAST(sum(1048576 // (size - 1)) AS BIGINT) AS rating FROM pins a JOIN pins b ON a.net = b.net AND a.node <> b.node AND a.node % 5 = b.node % 5 JOIN nets n ON n.net = a.net
        WHERE size >= 2 GROUP BY 1, 2) SELECT node, rep, rating FROM ok"""))
def _(spark, d):
    h, _p = w1(spark, d)
    return coarsen.rate(h, communities=h.nodes.select("node", (F.col("node") % 5).alias("community")))


@query("c10_matching", over("w1", f", {RATING}, {TARGET}, m AS (SELECT a.node, a.target FROM target a JOIN target b ON a.target = b.node AND b.target = a.node WHERE a.node < a.target) SELECT node, node AS rep FROM m UNION ALL SELECT target, node FROM m"))
def _(spark, d):
    return coarsen.matching(w1(spark, d)[0])


def _sub_round(i: int, share: int, shares: int, c_max: str) -> str:
    """SQL of one sub-round of deterministic clustering on c{i}(node, rep, single) to c{i + 1}; unit weights."""
    return f""",
        l{i} AS MATERIALIZED (SELECT rep, count(*) AS load FROM c{i} GROUP BY rep),
        q{i} AS MATERIALIZED (SELECT DISTINCT net, rep FROM pins JOIN c{i} USING (node)),
        g{i} AS (SELECT p.node, q.rep, sum(1048576 // (size - 1)) AS rating FROM pins p JOIN c{i} c ON c.node = p.node JOIN q{i} q ON q.net = p.net AND q.rep <> c.rep JOIN nets n ON n.net = p.net
            WHERE size >= 2 AND c.single AND (p.node * 7919 + 13) % {shares} = {share} GROUP BY 1, 2),
        w{i} AS MATERIALIZED (SELECT node, rep FROM (SELECT g.node, g.rep, row_number() OVER (PARTITION BY g.node ORDER BY rating DESC, g.rep) AS r FROM g{i} g JOIN l{i} l ON l.rep = g.rep WHERE load + 1 <= {c_max}) WHERE r = 1),
        s{i} AS (SELECT DISTINCT w.rep FROM w{i} w WHERE w.rep IN (SELECT node FROM w{i}) AND w.node < w.rep),
        k{i} AS (SELECT node, rep FROM w{i} WHERE node NOT IN (SELECT rep FROM s{i}) AND (rep NOT IN (SELECT node FROM w{i}) OR rep IN (SELECT rep FROM s{i}))),
        j{i} AS MATERIALIZED (SELECT node, rep FROM (SELECT k.node, k.rep, load + row_number() OVER (PARTITION BY k.rep ORDER BY k.node) AS now FROM k{i} k JOIN l{i} l ON l.rep = k.rep) WHERE now <= {c_max}),
        c{i + 1} AS MATERIALIZED (SELECT c.node, coalesce(j.rep, c.rep) AS rep, c.single AND j.node IS NULL AND c.node NOT IN (SELECT rep FROM j{i}) AS single FROM c{i} c LEFT JOIN j{i} j ON j.node = c.node)"""


@query("c11_det_clustering", over("w1", ", c0 AS (SELECT node, node AS rep, TRUE AS single FROM nodes)" + _sub_round(0, 0, 2, "7") + _sub_round(1, 1, 2, "7") + " SELECT node, rep FROM c2"))
def _(spark, d):
    return coarsen.deterministic(w1(spark, d)[0], 7, subrounds=2, tie="min_id", most=1e9)


@query("c06_round_limit", over("w1", f", {RATING}, {TARGET}, m AS (SELECT node, target, rating FROM target WHERE node % 2 = 1), k AS (SELECT node, target AS rep FROM m ORDER BY rating DESC, node LIMIT (SELECT count(*) - CAST(ceil(count(*) / 1.25) AS BIGINT) FROM nodes)) SELECT node, rep FROM k UNION ALL SELECT DISTINCT rep, rep FROM k WHERE rep NOT IN (SELECT node FROM k)"))
def _(spark, d):
    h, _p = w1(spark, d)
    t = truncate_lineage(coarsen.best_target(coarsen.rate(h), tie="min_id").filter("node % 2 = 1"), "targets")
    kept = coarsen.limit_round(t.select("node", F.col("target").alias("rep")), t, h.nodes.count(), 1.25).filter("node <> rep")
    return kept.union(kept.select(F.col("rep").alias("node"), "rep").distinct().join(kept.select("node"), "node", "left_anti"))


@query("c07_only_unclustered", over("w1", f", {RATING}, {TARGET}, cl AS (SELECT node, node - node % 2 AS rep FROM nodes WHERE node % 10 < 4) SELECT t.node, coalesce(c.rep, t.target) AS target FROM target t LEFT JOIN cl c ON c.node = t.target WHERE t.node NOT IN (SELECT node FROM cl)"))
def _(spark, d):
    h, _p = w1(spark, d)
    clustered = h.nodes.filter("node % 10 < 4").select("node", (F.col("node") - F.col("node") % 2).alias("rep"))
    return coarsen.open_wishes(coarsen.best_target(coarsen.rate(h), tie="min_id"), clustered)


MAP = "m AS (SELECT node, dense_rank() OVER (ORDER BY node % 500) - 1 AS coarse FROM nodes)"


def _clusters(h: Hypergraph) -> DataFrame:
    return h.nodes.select("node", (F.col("node") % 500).alias("rep"))


@query("k01_renumber", over("w1", f", {MAP} SELECT node, coarse FROM m"))
def _(spark, d):
    return contract.renumber(_clusters(w1(spark, d)[0]))


@query("k02_supernodes", over("w1", f", {MAP} SELECT coarse AS node, count(*) AS weight FROM m GROUP BY coarse"))
def _(spark, d):
    h, _p = w1(spark, d)
    return contract.coarse_nodes(h.nodes, contract.renumber(_clusters(h)))


@query("k03_coarse_pins", over("w1", f", {MAP} SELECT DISTINCT net, coarse AS node FROM pins JOIN m USING (node)"))
def _(spark, d):
    h, _p = w1(spark, d)
    return contract.coarse_pins(h.pins, contract.renumber(_clusters(h)))


@query("k04_single_pin", over("w1", f", {MAP} SELECT net, CAST(1 AS BIGINT) AS weight, CAST(count(DISTINCT coarse) AS INTEGER) AS size FROM pins JOIN m USING (node) GROUP BY net HAVING count(DISTINCT coarse) > 1"))
def _(spark, d):
    h, _p = w1(spark, d)
    return contract.drop_single(h.nets, contract.coarse_pins(h.pins, contract.renumber(_clusters(h))))[0]


for _w in ("w6", "w7"):

    @query(f"k05_identical_{_w}", over(_w, ", l AS (SELECT net, string_agg(node, ',' ORDER BY node) AS v FROM pins GROUP BY net) SELECT net, min(net) OVER (PARTITION BY v) AS kept FROM l"))
    def _(spark, d, w=_w):
        return contract.merge_identical(W.HYPERGRAPHS[w](spark, d))[1]

    @query(f"k05c_identical_hash_{_w}", SQL[f"k05_identical_{_w}"])
    def _(spark, d, w=_w):
        return contract.merge_identical(W.HYPERGRAPHS[w](spark, d), fingerprint="xx")[1]


@query("k06_project", over("w1", f", {MAP} SELECT node, CAST((coarse * 7919 + 13) % 8 AS INTEGER) AS block FROM m"))
def _(spark, d):
    h, _p = w1(spark, d)
    m = contract.renumber(_clusters(h))
    return contract.project(m.select(F.col("coarse").alias("node")).distinct().select("node", F.pmod(F.col("node") * 7919 + 13, F.lit(K)).cast("int").alias("block")), m)


@query("k07_prefix_sum", "SELECT o_orderkey, CAST(sum(o_custkey) OVER (ORDER BY o_orderkey) AS BIGINT) AS running FROM orders")
def _(spark, d):
    return prefix.running_sum(W.table(spark, d, "orders").select("o_orderkey", "o_custkey"), "o_orderkey", "o_custkey").select("o_orderkey", "running")


# -- communities ----------------------------------------------------------------------------------


@query("l06_edge_weights", over("w1", ", deg AS (SELECT node, count(*) AS g FROM pins GROUP BY node) SELECT 2 * p.node AS src, 2 * p.net + 1 AS dst, CAST((1048576 * g) // size AS BIGINT) AS w FROM pins p JOIN nets n ON n.net = p.net JOIN deg ON deg.node = p.node"))
def _(spark, d):
    return community.weighted_edges(w1(spark, d)[0], "degree")


@query("l04_volumes", over("w1", "SELECT community, CAST(sum(deg) AS BIGINT) AS vol FROM (SELECT (2 * node) % 7 AS community, 1048576 * count(*) AS deg FROM pins GROUP BY node UNION ALL SELECT (2 * net + 1) % 7, 1048576 * count(*) FROM pins GROUP BY net) GROUP BY community"))
def _(spark, d):
    e = community.weighted_edges(w1(spark, d)[0])
    a = community.both_ways(e)
    return community.volumes(a, a.select(F.col("src").alias("node"), (F.col("src") % 7).alias("community")).distinct())


@query("l03_move_round", over("w7", """, e AS (SELECT 2 * node AS src, 2 * net + 1 AS dst, CAST(1048576 AS HUGEINT) AS w FROM pins), a AS (SELECT src, dst, w FROM e UNION ALL SELECT dst, src, w FROM e),
        c AS (SELECT DISTINCT src AS node, src % 7 AS community FROM a), dg AS (SELECT src AS node, sum(w) AS deg FROM a GROUP BY src), v AS (SELECT community, sum(deg) AS vol FROM dg JOIN c USING (node) GROUP BY 1), tt AS (SELECT sum(deg) AS total FROM dg),
        t AS (SELECT a.src AS node, community, sum(w) AS w FROM a JOIN c ON c.node = a.dst GROUP BY 1, 2),
        g AS (SELECT t.node, h.community AS home, t.community, deg, (t.w - coalesce(s.w, 0)) * total - deg * (v.vol - vh.vol + deg) AS gain FROM t JOIN c h ON h.node = t.node AND h.community <> t.community LEFT JOIN t s ON s.node = t.node AND s.community = h.community
            JOIN dg ON dg.node = t.node JOIN v ON v.community = t.community JOIN v vh ON vh.community = h.community, tt)
        SELECT node, home AS src, community AS dst, CAST(deg AS BIGINT) AS deg FROM (SELECT *, row_number() OVER (PARTITION BY node ORDER BY gain DESC, community) AS r FROM g WHERE gain > 0) WHERE r = 1"""))
def _(spark, d):
    arcs = community.both_ways(community.weighted_edges(W.shared_lines(spark, d)))
    deg = arcs.groupBy(F.col("src").alias("node")).agg(F.sum("w").cast("long").alias("deg"))
    comm = deg.select("node", (F.col("node") % 7).alias("community"))
    return community.move_round(arcs, comm, deg, community.volumes(arcs, comm), int(deg.agg(F.sum("deg")).first()[0]))


@query("l05_volume_delta", over("w1", ", b AS (SELECT node % 7 AS community, node FROM nodes) SELECT CASE WHEN node % 3 = 0 THEN (node + 1) % 7 ELSE node % 7 END AS community, count(*) AS vol FROM nodes GROUP BY 1"))
def _(spark, d):
    n = w1(spark, d)[0].nodes
    vol = n.groupBy((F.col("node") % 7).alias("community")).agg(F.count("*").alias("vol"))
    moved = n.filter("node % 3 = 0").select("node", (F.col("node") % 7).alias("src"), ((F.col("node") + 1) % 7).alias("dst"), F.lit(1).cast("long").alias("deg"))
    return community.volume_delta(vol, moved)


@query("l07_modularity_w11", over("w2", """, lang AS (SELECT doc_id, dense_rank() OVER (ORDER BY lang) AS c FROM documents), l AS (SELECT net, min(c) AS c FROM pins JOIN lang ON node = doc_id GROUP BY net),
        e AS (SELECT d.c AS a, l.c AS b, p.node, p.net FROM pins p JOIN lang d ON d.doc_id = p.node JOIN l USING (net)), m AS (SELECT CAST(count(*) AS DOUBLE) AS m FROM e),
        v AS (SELECT c, CAST(count(*) AS DOUBLE) AS vol FROM (SELECT a AS c FROM e UNION ALL SELECT b FROM e) GROUP BY c)
        SELECT round((SELECT count(*) FROM e WHERE a = b) / m - (SELECT sum(vol * vol) FROM v) / (4 * m * m), 9) AS modularity FROM m"""))
def _(spark, d):
    h = W.document_tokens(spark, d)
    lang = W.table(spark, d, "documents").select(F.col("doc_id").alias("id"), F.ascii("lang").cast("long").alias("_a"), "lang")
    ids = prefix.dense_ids(lang, "lang", "c")
    doc = lang.join(F.broadcast(ids), "lang").select(F.col("id").alias("doc"), (F.col("c") + 1).alias("community"))
    net = h.pins.join(doc, F.col("node") == F.col("doc")).groupBy("net").agg(F.min("community").alias("community"))
    comm = doc.select((F.col("doc") * 2).alias("node"), "community").union(net.select((F.col("net") * 2 + 1).alias("node"), "community"))
    return community.modularity_df(community.weighted_edges(h), comm)


@query("l01_louvain_w7")
def _(spark, d):
    return community.louvain(W.shared_lines(spark, d), max_rounds=2, max_levels=2, subrounds=2)


# -- initial partitioning ---------------------------------------------------------------------------


#: Parts of recursive bisection on w1 by the reference partition: (k of all blocks, blocks of a part, eps).
PARTS = ((8, 8, 0.03), (8, 4, 0.03), (8, 2, 0.03), (6, 3, 0.05))


@query("i02_eps", f"""WITH nodes AS (SELECT DISTINCT l_partkey AS node FROM lineitem), p AS (SELECT * FROM (VALUES {", ".join(f"({k}, {kk}, {e}::DOUBLE)" for k, kk, e in PARTS)}) AS t(k, kk, e)),
        own AS (SELECT k, kk, e, CAST((node * 7919 + 13) % k // kk AS INTEGER) AS side, count(*) AS own FROM nodes, p GROUP BY 1, 2, 3, 4)
        SELECT k, kk, side, own, round(pow((1 + e) * (SELECT count(*) FROM nodes) / k * kk / own, 1.0 / ceil(log2(kk))) - 1, 9) AS eps FROM own""")
def _(spark, d):
    n = W.table(spark, d, "lineitem").select(F.col("l_partkey").alias("node")).filter("node is not null").distinct()
    parts = F.array(*[F.struct(F.lit(k).alias("k"), F.lit(kk).alias("kk"), F.lit(e).alias("e")) for k, kk, e in PARTS])
    x = n.select("node", F.explode(parts).alias("p")).select("node", "p.*")
    own = x.groupBy("k", "kk", "e", F.floor(F.pmod(F.col("node") * 7919 + 13, F.col("k")) / F.col("kk")).cast("int").alias("side")).agg(F.count("*").alias("own"))
    total = n.agg(F.count("*").alias("total"))
    eps = F.round(F.pow((1 + F.col("e")) * F.col("total") / F.col("k") * F.col("kk") / F.col("own"), 1 / F.ceil(F.log2("kk"))) - 1, 9)
    return own.crossJoin(F.broadcast(total)).select("k", "kk", "side", "own", eps.alias("eps"))


TRIALS = "v AS (SELECT 't' || o_orderkey % 9 AS technique, o_orderkey AS run, o_custkey % 3 AS overload, CAST(floor(o_totalprice / 100) AS BIGINT) AS km1 FROM orders)"


def _trials(spark, d):
    o = W.table(spark, d, "orders")
    return o.select(F.concat(F.lit("t"), (F.col("o_orderkey") % 9).cast("string")).alias("technique"), F.col("o_orderkey").alias("run"), (F.col("o_custkey") % 3).alias("overload"), F.floor(F.col("o_totalprice") / 100).cast("long").alias("km1"))


@query("i05_worth_rerun", f"WITH {TRIALS} SELECT technique, count(*) AS runs, round(avg(km1), 6) AS mean, round(stddev_samp(km1), 6) AS deviation, round(avg(km1), 6) - 2 * round(stddev_samp(km1), 6) <= (SELECT min(km1) FROM v) AS again FROM v GROUP BY technique")
def _(spark, d):
    return initial.worth_rerun(_trials(spark, d))


@query("i07_select_best", f"WITH {TRIALS} SELECT technique, run, overload, km1 FROM v ORDER BY overload, km1, technique, run LIMIT 1")
def _(spark, d):
    return initial.select_best(_trials(spark, d))


@query("i04_portfolio_w7")
def _(spark, d):
    return initial.portfolio(W.shared_lines(spark, d), EPS, repeats=kernels.RUNS[1])


# -- gains --------------------------------------------------------------------------------------------

GAINS = """pres AS (SELECT p.node, phi.block, count(*) AS w, count(*) FILTER (WHERE cnt = 1) AS alone FROM pins p JOIN phi USING (net) GROUP BY 1, 2),
        home AS (SELECT part.node, part.block AS own, pres.w AS total, pres.alone AS benefit FROM part JOIN pres ON pres.node = part.node AND pres.block = part.block)"""


@query("a01_gains", over("w1", f", {GAINS} SELECT pres.node, pres.block, CAST(benefit - total + w AS BIGINT) AS gain FROM pres JOIN home ON home.node = pres.node AND home.own <> pres.block"))
def _(spark, d):
    return gains.gains(*w1(spark, d))


@query("a02_gain_table", over("w1", f", {GAINS} SELECT pres.node, pres.block, w AS w_present, benefit FROM pres JOIN home USING (node)"))
def _(spark, d):
    b, p = gains.gain_table(*w1(spark, d))
    return p.join(b, "node")


AFTER = f"{MOVES}, part2 AS (SELECT part.node, CAST(coalesce(dst, block) AS INTEGER) AS block FROM part LEFT JOIN moves USING (node))"


@query("a03_delta", over("w1", f""", {AFTER}, phi2 AS (SELECT net, block, count(*) AS cnt FROM pins JOIN part2 USING (node) GROUP BY 1, 2),
        pres AS (SELECT p.node, phi2.block, count(*) AS w, count(*) FILTER (WHERE cnt = 1) AS alone FROM pins p JOIN phi2 USING (net) GROUP BY 1, 2), home AS (SELECT part2.node, pres.alone AS benefit FROM part2 JOIN pres USING (node, block))
        SELECT pres.node, pres.block, w AS w_present, benefit FROM pres JOIN home USING (node)"""))
def _(spark, d):
    h, p = w1(spark, d)
    b, x = gains.gain_table(h, p)
    b, x = gains.apply_delta(truncate_lineage(b, "benefit"), truncate_lineage(x, "present"), h, p, reference_moves(h, p))
    return x.join(b, "node")


@query("a04b_block_benefits", over("w1", "SELECT p.node, phi.block, CAST(count(*) FILTER (WHERE cnt - CASE WHEN phi.block = part.block THEN 1 ELSE 0 END = 0) AS BIGINT) AS benefit FROM pins p JOIN phi USING (net) JOIN part ON part.node = p.node GROUP BY 1, 2"))
def _(spark, d):
    return gains.block_benefits(*w1(spark, d))


@query("a06_apply", over("w1", f""", {MOVES}, w AS (SELECT block, count(*) AS w FROM part GROUP BY block), r AS (SELECT moves.*, row_number() OVER (PARTITION BY dst ORDER BY idx) + w.w AS after FROM moves JOIN w ON w.block = moves.dst)
        SELECT idx, node, src, CAST(dst AS INTEGER) AS dst FROM r WHERE after <= floor(1.03 * ceil((SELECT count(*) FROM nodes) / 8.0) + 1e-9)"""))
def _(spark, d):
    h, p = w1(spark, d)
    return gains.apply_moves(h, p, reference_moves(h, p), metrics.max_block_weight(metrics.total_weight(h), K, EPS))[1]


SIDES = """s AS (SELECT p.net, part.block, m.idx AS o, CAST(NULL AS BIGINT) AS i, CASE WHEN m.idx IS NULL THEN 1 ELSE 0 END AS st FROM pins p JOIN part ON part.node = p.node LEFT JOIN moves m ON m.node = p.node
        UNION ALL SELECT p.net, m.dst, CAST(NULL AS BIGINT), m.idx, 0 FROM pins p JOIN moves m ON m.node = p.node),
        g AS (SELECT net, block, max(o) AS o, min(i) AS i, sum(st) AS st FROM s GROUP BY 1, 2),
        d AS (SELECT o AS idx, 1 AS v FROM g WHERE st = 0 AND o IS NOT NULL AND (i IS NULL OR o < i) UNION ALL SELECT i, -1 FROM g WHERE st = 0 AND i IS NOT NULL AND (o IS NULL OR i > o)),
        ex AS (SELECT moves.idx, node, CAST(coalesce(sum(v), 0) AS BIGINT) AS gain FROM moves LEFT JOIN d ON d.idx = moves.idx GROUP BY moves.idx, node)"""


@query("a09_recalculate", over("w1", f", {MOVES}, {SIDES} SELECT idx, node, gain FROM ex"))
def _(spark, d):
    h, p = w1(spark, d)
    return gains.recalculate(h, p, reference_moves(h, p))


@query("a07_attributed", over("w1", f", {AFTER}, l2 AS (SELECT net, count(DISTINCT block) AS la FROM pins JOIN part2 USING (node) GROUP BY net) SELECT CAST((SELECT sum(la) FROM lam) - (SELECT sum(la) FROM l2) AS BIGINT) AS total"))
def _(spark, d):
    h, p = w1(spark, d)
    return gains.attributed(h, p, reference_moves(h, p)).agg(F.sum("gain").cast("long").alias("total"))


@query("a10_best_prefix", over("w1", f""", {MOVES}, {SIDES}, lm AS (SELECT floor(1.03 * ceil((SELECT count(*) FROM nodes) / 8.0) + 1e-9) AS l), w0 AS (SELECT block, count(*) AS w FROM part GROUP BY block),
        c AS (SELECT e.idx, sum(gain) OVER (ORDER BY e.idx) AS total FROM ex e), ch AS (SELECT idx, src AS block, -1 AS v FROM moves UNION ALL SELECT idx, dst, 1 FROM moves),
        st AS (SELECT i.idx, b.block, b.w + coalesce((SELECT sum(v) FROM ch WHERE ch.block = b.block AND ch.idx <= i.idx), 0) AS w, b.w AS first FROM moves i CROSS JOIN w0 b),
        ok AS (SELECT idx FROM st, lm GROUP BY idx HAVING bool_and(w <= greatest(l, first))), best AS (SELECT idx, total FROM c JOIN ok USING (idx) WHERE total > 0 ORDER BY total DESC, idx LIMIT 1)
        SELECT CAST(coalesce((SELECT idx FROM best), -1) AS BIGINT) AS idx, CAST(coalesce((SELECT total FROM best), 0) AS BIGINT) AS gain"""))
def _(spark, d):
    h, p = w1(spark, d)
    m = truncate_lineage(reference_moves(h, p), "moves")
    return gains.best_prefix(gains.recalculate(h, p, m), m, h, p, K, metrics.max_block_weight(metrics.total_weight(h), K, EPS))


@query("a11_pair_matching", over("w1", f", {MOVES} SELECT idx, node, src, CAST(dst AS INTEGER) AS dst FROM moves WHERE CASE WHEN greatest(src, dst) = 7 THEN (2 * least(src, dst)) % 7 ELSE (src + dst) % 7 END = 3"))
def _(spark, d):
    h, p = w1(spark, d)
    return gains.deconflict(reference_moves(h, p), "pair_matching", K, 3)


@query("a11_oriented", over("w1", f", {MOVES} SELECT idx, node, src, CAST(dst AS INTEGER) AS dst FROM moves WHERE src < dst"))
def _(spark, d):
    h, p = w1(spark, d)
    return gains.deconflict(reference_moves(h, p), "oriented")


@query("a11_color", over("w1", f""", {MOVES}, x AS (SELECT p.net, m.node, (m.node * 7919 + 13) % 1048573 AS h FROM pins p JOIN moves m ON m.node = p.node),
        lost AS (SELECT DISTINCT node FROM (SELECT node, row_number() OVER (PARTITION BY net ORDER BY h, node) AS r FROM x) WHERE r > 1)
        SELECT idx, node, src, CAST(dst AS INTEGER) AS dst FROM moves WHERE node NOT IN (SELECT node FROM lost)"""))
def _(spark, d):
    h, p = w1(spark, d)
    return gains.deconflict(reference_moves(h, p), "color", h=h)


# -- refinement -----------------------------------------------------------------------------------------

WISH = f"{GAINS}, best AS (SELECT node, own AS src, block AS dst, gain FROM (SELECT pres.node, own, pres.block, benefit - total + w AS gain, row_number() OVER (PARTITION BY pres.node ORDER BY benefit - total + w DESC, pres.block) AS r FROM pres JOIN home ON home.node = pres.node AND home.own <> pres.block) WHERE r = 1 AND gain > 0)"


@query("r01_best_moves", over("w1", f", {WISH} SELECT node, src, dst, CAST(gain AS BIGINT) AS gain FROM best"))
def _(spark, d):
    return refine.best_moves(*w1(spark, d))


@query("r05_det_swaps", over("w1", f""", {WISH}, w AS (SELECT block, count(*) AS w FROM part GROUP BY block), room AS (SELECT block, greatest(floor(1.03 * ceil((SELECT count(*) FROM nodes) / 8.0) + 1e-9) - w, 0) AS room FROM w),
        x AS (SELECT *, least(src, dst) AS s, greatest(src, dst) AS t, CASE WHEN src > dst THEN 1 ELSE 0 END AS side, row_number() OVER (PARTITION BY src, dst ORDER BY gain DESC, node) AS rk FROM best),
        y AS (SELECT *, sum(CASE WHEN side = 0 THEN 1 ELSE -1 END) OVER (PARTITION BY s, t ORDER BY rk, side) AS x, row_number() OVER (PARTITION BY s, t ORDER BY rk, side) AS step FROM x),
        l AS (SELECT s, t, max(step) AS last FROM y JOIN room rs ON rs.block = s JOIN room rt ON rt.block = t WHERE x <= rt.room AND -x <= rs.room GROUP BY s, t)
        SELECT node, src, dst, CAST(gain AS BIGINT) AS gain FROM y JOIN l USING (s, t) WHERE step <= last"""))
def _(spark, d):
    h, p = w1(spark, d)
    return refine.swaps(refine.best_moves(h, p), h, refine.slack_of(h, p, K, metrics.max_block_weight(metrics.total_weight(h), K, EPS)))


@query("r05e_equal_swaps", over("w1", f""", {WISH}, x AS (SELECT *, least(src, dst) AS s, greatest(src, dst) AS t, row_number() OVER (PARTITION BY src, dst ORDER BY gain DESC, node) AS rk FROM best),
        n AS (SELECT s, t, least(count(*) FILTER (WHERE src < dst), count(*) FILTER (WHERE src > dst)) AS n FROM x GROUP BY s, t) SELECT node, src, dst, CAST(gain AS BIGINT) AS gain FROM x JOIN n USING (s, t) WHERE rk <= n"""))
def _(spark, d):
    return refine.swap_equal_counts(refine.best_moves(*w1(spark, d)))


LAYERS = """two AS (SELECT node, block FROM part WHERE block IN (0, 1)), q AS MATERIALIZED (SELECT net, node, block FROM pins JOIN two USING (node)), cutn AS (SELECT net FROM q GROUP BY net HAVING count(DISTINCT block) = 2),
        l0 AS MATERIALIZED (SELECT DISTINCT node, block FROM q WHERE net IN (SELECT net FROM cutn)),
        n1 AS (SELECT DISTINCT q.node, q.block FROM q JOIN (SELECT DISTINCT q.net, q.block FROM q JOIN l0 USING (node)) a ON a.net = q.net AND a.block = q.block), l1 AS MATERIALIZED (SELECT * FROM n1 WHERE node NOT IN (SELECT node FROM l0)),
        n2 AS (SELECT DISTINCT q.node, q.block FROM q JOIN (SELECT DISTINCT q.net, q.block FROM q JOIN l1 USING (node)) a ON a.net = q.net AND a.block = q.block), l2 AS (SELECT * FROM n2 WHERE node NOT IN (SELECT node FROM l0 UNION SELECT node FROM l1)),
        reg AS MATERIALIZED (SELECT node, block, 0 AS hop FROM l0 UNION ALL SELECT node, block, 1 FROM l1 UNION ALL SELECT node, block, 2 FROM l2)"""


@query("fl05_region_layers", over("w1", f", {LAYERS} SELECT node, block, hop FROM reg"))
def _(spark, d):
    return refine.region_layers(*w1(spark, d), 0, 1)


NET = f"""{LAYERS}, y AS (SELECT DISTINCT q.net, CASE WHEN r.node IS NOT NULL THEN q.node WHEN q.block = 0 THEN -1 ELSE -2 END AS vertex FROM q LEFT JOIN (SELECT node FROM reg WHERE hop = 0) r ON r.node = q.node),
        kp AS (SELECT net FROM y GROUP BY net HAVING count(*) > 1 AND max(vertex) >= 0 OR count(*) = 2), fn AS (SELECT net, vertex, CAST(1 AS BIGINT) AS weight FROM y WHERE net IN (SELECT net FROM kp))"""


@query("fl06_network", over("w1", f", {NET} SELECT net, vertex, weight FROM fn"))
def _(spark, d):
    h, p = w1(spark, d)
    return refine.network(h, p, refine.region_layers(h, p, 0, 1, depth=0), 0, 1)


@query("fl07_expansion", over("w1", f", {NET} SELECT 'i' || net AS src, 'o' || net AS dst, weight AS cap FROM (SELECT DISTINCT net, weight FROM fn) UNION ALL SELECT 'v' || vertex, 'i' || net, weight FROM fn UNION ALL SELECT 'o' || net, 'v' || vertex, weight FROM fn"))
def _(spark, d):
    h, p = w1(spark, d)
    return refine.expansion(refine.network(h, p, refine.region_layers(h, p, 0, 1, depth=0), 0, 1))


# -- n-level ----------------------------------------------------------------------------------------------

FOREST = "f AS (SELECT node, CAST(node % 50 AS BIGINT) AS parent, CAST((node * 37) % 101 AS BIGINT) AS t_start, CAST((node * 37) % 101 + node % 7 AS BIGINT) AS t_end FROM nodes WHERE node % 50 <> node)"


@query("n04_sibling_groups", over("w1", f""", {FOREST}, x AS (SELECT *, max(t_end) OVER (PARTITION BY parent ORDER BY t_start, t_end, node ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS reach FROM f)
        SELECT node, parent, CAST(sum(CASE WHEN reach IS NULL OR t_start > reach THEN 1 ELSE 0 END) OVER (PARTITION BY parent ORDER BY t_start, t_end, node) AS BIGINT) AS grp FROM x"""))
def _(spark, d):
    n = w1(spark, d)[0].nodes.filter("node % 50 <> node")
    return nlevel.sibling_groups(n.select("node", (F.col("node") % 50).alias("parent"), (F.col("node") * 37 % 101).alias("t_start"), (F.col("node") * 37 % 101 + F.col("node") % 7).alias("t_end")))


def _two_steps(spark, d):
    h, _p = w1(spark, d)
    n = h.nodes.select("node")
    here = n.select(F.col("node").alias("parent"))
    a = n.filter("node % 4 = 1").select("node", (F.col("node") + 1).alias("parent"), F.lit(0).cast("long").alias("tau"))
    b = n.filter("node % 4 = 2").select("node", (F.col("node") + 1).alias("parent"), F.lit(1).cast("long").alias("tau"))
    return h, truncate_lineage(a.union(b).join(here, "parent", "left_semi").select("node", "parent", "tau"), "forest")


@query("n01_contract", over("w1", "SELECT net, CASE WHEN node = 5 THEN 6 ELSE node END AS node FROM pins GROUP BY 1, 2"))
def _(spark, d):
    h, _p = w1(spark, d)
    v = h.pins.select("net", "node", F.lit(0).cast("long").alias("valid_from"), F.lit(1 << 62).alias("valid_to"))
    return nlevel.active(nlevel.contract_pair(v, 5, 6, 1), 1)


@query("n01_uncontract", over("w1", "SELECT net, node FROM pins"))
def _(spark, d):
    h, _p = w1(spark, d)
    v = h.pins.select("net", "node", F.lit(0).cast("long").alias("valid_from"), F.lit(1 << 62).alias("valid_to"))
    return nlevel.active(nlevel.uncontract_pair(nlevel.contract_pair(v, 5, 6, 1), 5, 6, 1), 1)


UP = """f0 AS (SELECT node, node + 1 AS parent FROM nodes WHERE node % 4 = 1 AND node + 1 IN (SELECT node FROM nodes)), f1 AS (SELECT node, node + 1 AS parent FROM nodes WHERE node % 4 = 2 AND node + 1 IN (SELECT node FROM nodes)),
        r1 AS (SELECT n.node, coalesce(parent, n.node) AS root FROM nodes n LEFT JOIN f0 USING (node)), r2 AS (SELECT r1.node, coalesce(parent, root) AS root FROM r1 LEFT JOIN f1 ON f1.node = r1.root)"""


@query("n06_active_pins", over("w1", f", {UP} SELECT 1 AS tau, net, root AS node FROM pins JOIN r1 USING (node) GROUP BY ALL UNION ALL SELECT 2, net, root FROM pins JOIN r2 USING (node) GROUP BY ALL"))
def _(spark, d):
    h, f = _two_steps(spark, d)
    v = truncate_lineage(nlevel.versioned_pins(h, f), "versions")
    one = lambda t: nlevel.active(v, t).select(F.lit(t).alias("tau"), "net", "node")
    return one(1).union(one(2))


@query("n07_clean", over("w1", f", {UP}, q AS (SELECT DISTINCT net, root AS node FROM pins JOIN r2 USING (node)), l AS (SELECT net, string_agg(node, ',' ORDER BY node) AS v, count(*) AS c FROM q GROUP BY net) SELECT min(net) AS net, CAST(count(*) AS BIGINT) AS weight FROM l WHERE c > 1 GROUP BY v"))
def _(spark, d):
    h, f = _two_steps(spark, d)
    pins = truncate_lineage(nlevel.active(nlevel.versioned_pins(h, f), 2), "active")
    nets, pins = contract.drop_single(h.nets, pins)
    return contract.merge_identical(Hypergraph(h.nodes, nets, pins))[0].nets.select("net", "weight")


@query("n05_batches")
def _(spark, d):
    return nlevel.batches(_two_steps(spark, d)[1], 100)


@query("n02_forest_w7")
def _(spark, d):
    return nlevel.coarsen_forest(W.shared_lines(spark, d), 2, per_block=100, max_passes=6)[0]


# -- plain graphs -------------------------------------------------------------------------------------------

EDGES = "edges AS MATERIALIZED (SELECT a.node AS src, b.node AS dst, count(*) AS weight FROM pins a JOIN pins b ON a.net = b.net AND a.node < b.node GROUP BY 1, 2), arcs AS (SELECT src, dst, weight FROM edges UNION ALL SELECT dst, src, weight FROM edges)"


@query("p01_copies_w13", over("w1", f", {EDGES} SELECT src, dst, weight FROM arcs"))
def _(spark, d):
    return graphs.arcs(W.co_purchases(spark, d))


@query("p03_contract_w13", over("w1", f", {EDGES} SELECT least(src % 100, dst % 100) AS src, greatest(src % 100, dst % 100) AS dst, CAST(sum(weight) AS BIGINT) AS weight FROM edges WHERE src % 100 <> dst % 100 GROUP BY 1, 2"))
def _(spark, d):
    h, _p = w1(spark, d)
    return graphs.contract(W.co_purchases(spark, d), h.nodes.select("node", (F.col("node") % 100).alias("coarse")))


@query("p04_gain_w13", over("w1", f", {EDGES}, t AS (SELECT src AS node, block, sum(weight) AS w FROM arcs JOIN part ON part.node = arcs.dst GROUP BY 1, 2) SELECT t.node, t.block, CAST(t.w - coalesce(o.w, 0) AS BIGINT) AS gain FROM t JOIN part p ON p.node = t.node AND p.block <> t.block LEFT JOIN t o ON o.node = t.node AND o.block = p.block"))
def _(spark, d):
    return graphs.gains(W.co_purchases(spark, d), w1(spark, d)[1])


@query("p04_delta_w13", over("w1", f", {EDGES}, {AFTER} SELECT src AS node, block, CAST(sum(weight) AS BIGINT) AS w FROM arcs JOIN part2 ON part2.node = arcs.dst GROUP BY 1, 2"))
def _(spark, d):
    h, p = w1(spark, d)
    e = truncate_lineage(W.co_purchases(spark, d), "edges")
    return graphs.apply_delta(graphs.gain_table(e, p), e, p, reference_moves(h, p))


@query("p05_attributed_w13", over("w1", f""", {EDGES}, {MOVES}, x AS (SELECT m.idx, weight, m.src AS a, m.dst AS b, CASE WHEN o.idx < m.idx THEN o.dst ELSE q.block END AS there FROM arcs JOIN moves m ON m.node = arcs.src JOIN part q ON q.node = arcs.dst LEFT JOIN moves o ON o.node = arcs.dst)
        SELECT m.idx, m.node, CAST(coalesce(sum(weight * (CASE WHEN a <> there THEN 1 ELSE 0 END - CASE WHEN b <> there THEN 1 ELSE 0 END)), 0) AS BIGINT) AS gain FROM moves m LEFT JOIN x ON x.idx = m.idx GROUP BY m.idx, m.node"""))
def _(spark, d):
    h, p = w1(spark, d)
    return graphs.attributed(W.co_purchases(spark, d), p, reference_moves(h, p))


@query("p06_edge_cut_w13", over("w1", f", {EDGES} SELECT CAST(sum(weight) AS BIGINT) AS cut FROM edges JOIN part a ON a.node = src JOIN part b ON b.node = dst WHERE a.block <> b.block"))
def _(spark, d):
    return graphs.edge_cut(W.co_purchases(spark, d), w1(spark, d)[1])


@query("p07_rate_w13", over("w1", f", {EDGES} SELECT src AS node, dst AS rep, weight AS rating FROM arcs"))
def _(spark, d):
    return graphs.rate(W.co_purchases(spark, d))


@query("w16_nation_trade", """SELECT least(c_nationkey, s_nationkey)::BIGINT AS src, greatest(c_nationkey, s_nationkey)::BIGINT AS dst, count(*) AS weight FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
        JOIN supplier ON l_suppkey = s_suppkey WHERE c_nationkey <> s_nationkey GROUP BY 1, 2""")
def _(spark, d):
    return W.nation_trade(spark, d)


@query("op_knn", """WITH v AS (SELECT vec_id AS id, embedding::DOUBLE[] AS v FROM embeddings), n AS (SELECT id, v, sqrt(list_dot_product(v, v)) AS n FROM v),
        s AS (SELECT a.id AS a, b.id AS b, round(list_dot_product(a.v, b.v) / (a.n * b.n), 6) AS s FROM n a JOIN n b ON a.id <> b.id) SELECT a, b FROM (SELECT *, row_number() OVER (PARTITION BY a ORDER BY s DESC, b) AS r FROM s) WHERE r <= 4""")
def _(spark, d):
    return graphs.knn(W.table(spark, d, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("v")), 4)


# -- evaluation of runs -----------------------------------------------------------------------------------------

RUNS = """WITH runs AS (SELECT o_custkey % 50 AS instance, o_orderkey % 4 AS algo, o_orderkey AS seed, CASE o_orderkey % 3 WHEN 0 THEN 1 WHEN 1 THEN 4 ELSE 16 END AS threads, CAST(floor(o_totalprice / 100) + 1 AS BIGINT) AS quality,
        (o_orderkey * 37 + o_custkey) % 400 + 1 AS seconds, CASE WHEN o_orderkey % 29 = 0 THEN 'timeout' WHEN o_orderkey % 17 = 0 THEN 'infeasible' ELSE 'ok' END AS status FROM orders),
        q AS (SELECT instance, algo, round(avg(quality) FILTER (WHERE status = 'ok'), 6) AS quality FROM runs GROUP BY 1, 2),
        t AS (SELECT instance, algo, avg(CASE WHEN status = 'timeout' THEN 400 ELSE least(seconds, 400) END) AS t FROM runs GROUP BY 1, 2),
        pairs AS (SELECT a.instance, a.quality AS qa, b.quality AS qb FROM q a JOIN q b ON a.instance = b.instance AND a.algo = 0 AND b.algo = 1 WHERE a.quality IS NOT NULL AND b.quality IS NOT NULL)
        """


def runs_query(name: str, sql: str):
    return query(name, RUNS + sql)


@runs_query("q06_times", "SELECT algo, round(exp(avg(ln(t))), 6) AS gmean FROM t GROUP BY algo")
def _(spark, d):
    return evaluate.times(W.run_logs(spark, d))


@runs_query("q07_quality", "SELECT instance, algo, quality FROM q")
def _(spark, d):
    return evaluate.quality(W.run_logs(spark, d))


@runs_query("q08_pareto", """, o AS (SELECT instance, algo, avg(quality) AS q, avg(seconds) AS t FROM runs WHERE status = 'ok' GROUP BY 1, 2), r AS (SELECT algo, min(q) OVER (PARTITION BY instance) / q AS iq, min(t) OVER (PARTITION BY instance) / t AS it FROM o),
        p AS (SELECT algo, round(count(*) / sum(iq), 6) AS quality, round(count(*) / sum(it), 6) AS seconds FROM r GROUP BY algo)
        SELECT algo, quality, seconds, NOT EXISTS (SELECT 1 FROM p x WHERE x.quality <= p.quality AND x.seconds <= p.seconds AND (x.quality < p.quality OR x.seconds < p.seconds)) AS front FROM p""")
def _(spark, d):
    return evaluate.pareto(W.run_logs(spark, d))


@runs_query("q09_slowdown", "SELECT round(exp(avg(ln(a.t / b.t))), 6) AS ratio, count(*) AS instances FROM t a JOIN t b ON a.instance = b.instance AND a.algo = 0 AND b.algo = 1")
def _(spark, d):
    return evaluate.slowdown(W.run_logs(spark, d), 0, 1)


@runs_query("q10_profile", ", g(tau) AS (VALUES (1.0::DOUBLE), (1.05), (1.1), (1.5)), b AS (SELECT *, min(quality) OVER (PARTITION BY instance) AS best FROM q) SELECT algo, tau, round(avg(CASE WHEN quality <= tau * best THEN 1.0::DOUBLE ELSE 0.0 END), 6) AS share FROM b, g GROUP BY 1, 2")
def _(spark, d):
    return evaluate.profile(W.run_logs(spark, d), [1.0, 1.05, 1.1, 1.5])


@runs_query("q11_effectiveness", """, x AS (SELECT *, (seed * 7919 + draw * 104729 + algo * 31) % 65537 AS h FROM runs, (SELECT unnest(range(10)) AS draw) WHERE status = 'ok' AND algo IN (0, 1)),
        y AS (SELECT *, row_number() OVER w AS n, coalesce(sum(seconds) OVER (PARTITION BY instance, algo, draw ORDER BY h, seed ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM x WINDOW w AS (PARTITION BY instance, algo, draw ORDER BY h, seed)),
        f AS (SELECT a.instance, a.draw, a.seconds AS ta, b.seconds AS tb FROM y a JOIN y b ON a.instance = b.instance AND a.draw = b.draw AND a.n = 1 AND b.n = 1 AND a.algo = 0 AND b.algo = 1),
        z AS (SELECT y.*, ta, tb, greatest(ta, tb) AS slow, ((h * 31 + 17) % 1000) / 1000.0 AS u FROM y JOIN f USING (instance, draw)),
        k AS (SELECT * FROM z WHERE n = 1 OR ((CASE WHEN algo = 0 THEN ta < tb ELSE tb < ta END) AND before < slow AND (before + seconds <= slow OR u < (slow - before) / seconds)))
        SELECT instance, draw, min(quality) FILTER (WHERE algo = 0) AS qa, min(quality) FILTER (WHERE algo = 1) AS qb FROM k GROUP BY 1, 2""")
def _(spark, d):
    return evaluate.effectiveness(W.run_logs(spark, d), 0, 1)


@runs_query("q12_wilcoxon", """, d AS (SELECT qa - qb AS d FROM pairs WHERE qa <> qb), r AS (SELECT d, rank() OVER (ORDER BY abs(d)) + (count(*) OVER (PARTITION BY abs(d)) - 1) / 2.0 AS r, count(*) OVER (PARTITION BY abs(d)) AS c FROM d),
        s AS (SELECT count(*) AS n, coalesce(sum(r) FILTER (WHERE d > 0), 0) AS w, coalesce(sum((c * c - 1) / 48.0), 0) AS t FROM r)
        SELECT n, round(w, 6)::DOUBLE AS w_plus, round((w - n * (n + 1) / 4.0) / sqrt(n * (n + 1) * (2 * n + 1) / 24.0 - t), 6) AS z, abs(round((w - n * (n + 1) / 4.0) / sqrt(n * (n + 1) * (2 * n + 1) / 24.0 - t), 6)) > 2.576 AS significant FROM s""")
def _(spark, d):
    return evaluate.wilcoxon(W.run_logs(spark, d), 0, 1)


@runs_query("q13_median_gain", "SELECT round((quantile_cont(qb / qa, 0.5) - 1) * 100, 6) AS percent FROM pairs")
def _(spark, d):
    return evaluate.median_improvement(W.run_logs(spark, d), 0, 1)


@runs_query("q14_win_share", "SELECT round(avg((qa < qb)::INT), 6) AS better, round(avg((qa = qb)::INT), 6) AS equal FROM pairs")
def _(spark, d):
    return evaluate.win_share(W.run_logs(spark, d), 0, 1)


@runs_query("q15_speedup", """, m AS (SELECT instance, algo, threads, avg(seconds) AS t FROM runs WHERE status = 'ok' GROUP BY 1, 2, 3), s AS (SELECT b.threads, a.t AS t1, a.t / b.t AS s FROM m a JOIN m b ON a.instance = b.instance AND a.algo = b.algo AND a.threads = 1 AND b.threads > 1)
        SELECT threads::BIGINT AS threads, round(exp(avg(ln(s))), 6) AS gmean, round(exp(avg(ln(s)) FILTER (WHERE t1 >= 200)), 6) AS gmean_long, round(avg((s > 1)::INT), 6) AS share FROM s GROUP BY threads""")
def _(spark, d):
    return evaluate.speedup(W.run_logs(spark, d))


@runs_query("q16_rolling", ", s AS (SELECT instance, avg(t) AS t FROM t GROUP BY instance) SELECT instance, round(exp(avg(ln(t)) OVER (ORDER BY instance ROWS BETWEEN 12 PRECEDING AND 12 FOLLOWING)), 6) AS rolling FROM s")
def _(spark, d):
    r = W.run_logs(spark, d)
    s = F.when(F.col("status") == "timeout", F.lit(400)).otherwise(F.least("seconds", F.lit(400)))
    t = r.groupBy("instance", "algo").agg(F.avg(s).alias("t")).groupBy("instance").agg(F.avg("t").alias("t"))
    return evaluate.rolling_gmean(t, "instance", "t").select("instance", "rolling")


@runs_query("q17_shares", ", e AS (SELECT instance, algo AS phase, sum(seconds) AS s FROM runs GROUP BY 1, 2), s AS (SELECT phase, s / sum(s) OVER (PARTITION BY instance) AS share FROM e) SELECT phase, round(quantile_cont(share, 0.5), 6) AS median, count(*) AS instances FROM s GROUP BY phase")
def _(spark, d):
    return evaluate.component_shares(W.run_logs(spark, d).select("instance", F.col("algo").alias("phase"), "seconds"))


@runs_query("q17_curve", """, e AS (SELECT instance, algo AS phase, sum(seconds) AS s FROM runs GROUP BY 1, 2), s AS (SELECT phase, round(s / sum(s) OVER (PARTITION BY instance), 6) AS share FROM e)
        SELECT DISTINCT phase, share, round(cume_dist() OVER (PARTITION BY phase ORDER BY share DESC), 6) AS reached FROM s""")
def _(spark, d):
    return evaluate.share_curve(W.run_logs(spark, d).select("instance", F.col("algo").alias("phase"), "seconds"))


@runs_query("q18_infeasible", ", x AS (SELECT instance, algo, bool_and(status = 'infeasible') AS none FROM runs GROUP BY 1, 2) SELECT algo, round(avg(none::INT), 6) AS share, round(avg(none::INT), 6) > 0.15 AS flagged FROM x GROUP BY algo")
def _(spark, d):
    return evaluate.infeasible_share(W.run_logs(spark, d))


@runs_query("q20_mismatch", "SELECT count(*) AS n, round(avg((seconds % 50 <> quality % 50)::INT), 6) AS mismatch, round(avg((quality % 50 < 10)::INT), 6) AS negative FROM runs")
def _(spark, d):
    r = W.run_logs(spark, d)
    return evaluate.gain_mismatch(r.select((F.col("seconds") % 50 - 10).alias("expected"), (F.col("quality") % 50 - 10).alias("attributed")))


@runs_query("op_agg_rollup", "SELECT algo, status, count(*) AS n, CAST(sum(quality) AS BIGINT) AS quality, CAST(grouping(algo, status) AS BIGINT) AS level FROM runs GROUP BY ROLLUP (algo, status)")
def _(spark, d):
    return evaluate.rollup_quality(W.run_logs(spark, d))


@runs_query("op_agg_cube", "SELECT algo, CAST(threads AS BIGINT) AS threads, count(*) AS n, CAST(sum(seconds) AS BIGINT) AS seconds, CAST(grouping(algo, threads) AS BIGINT) AS level FROM runs GROUP BY CUBE (algo, threads)")
def _(spark, d):
    return evaluate.cube_quality(W.run_logs(spark, d))


@runs_query("op_agg_pivot", "SELECT algo, CAST(sum(quality) FILTER (WHERE threads = 1) AS BIGINT) AS t1, CAST(sum(quality) FILTER (WHERE threads = 4) AS BIGINT) AS t4, CAST(sum(quality) FILTER (WHERE threads = 16) AS BIGINT) AS t16 FROM runs GROUP BY algo")
def _(spark, d):
    return evaluate.pivot_quality(W.run_logs(spark, d))


# -- operators around the methods ---------------------------------------------------------------------------------


@query("op_join_asof", "SELECT c.o_orderkey, c.o_custkey, e.event_id FROM orders c ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events GROUP BY 1, 2) e ON c.o_custkey = e.user_id AND c.o_orderdate >= e.ts")
def _(spark, d):
    o = W.table(spark, d, "orders").select("o_orderkey", F.col("o_custkey").alias("key"), F.col("o_orderdate").alias("at"))
    e = W.table(spark, d, "events").select(F.col("user_id").alias("key"), F.col("ts").alias("at"), "event_id")
    return joins.asof(o, e, "at", "key", "event_id").select("o_orderkey", F.col("key").alias("o_custkey"), "event_id")


@query("op_join_range", "SELECT o_orderkey, p_partkey FROM orders JOIN part ON o_custkey >= p_partkey AND o_custkey < p_partkey + p_size")
def _(spark, d):
    o = W.table(spark, d, "orders").select("o_orderkey", "o_custkey")
    p = W.table(spark, d, "part").select("p_partkey", (F.col("p_partkey") + F.col("p_size")).alias("end"))
    return joins.range_bucketed(o, p, "o_custkey", "p_partkey", "end", 32).select("o_orderkey", "p_partkey")


@query("op_join_salted", "SELECT l_orderkey, l_linenumber, s_name FROM lineitem JOIN supplier ON l_suppkey = s_suppkey")
def _(spark, d):
    li = W.table(spark, d, "lineitem").select(F.col("l_suppkey").alias("s_suppkey"), "l_orderkey", "l_linenumber")
    return joins.salted(li, W.table(spark, d, "supplier").select("s_suppkey", "s_name"), "s_suppkey").select("l_orderkey", "l_linenumber", "s_name")


@query("op_join_anti", "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
def _(spark, d):
    return W.table(spark, d, "orders").select("o_orderkey").join(W.table(spark, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey")), "o_orderkey", "left_anti")


@query("op_win_rank", over("w1", "SELECT net, rank() OVER (ORDER BY size DESC) AS r FROM nets"))
def _(spark, d):
    # a rank is one more than the rows before it: a prefix sum over the distinct values, not a window over all rows
    n = w1(spark, d)[0].nets.select("net", "size")
    before = prefix.running_sum(n.groupBy((-F.col("size")).alias("key")).agg(F.count("*").alias("c")), "key", "c", "before", exclusive=True)
    return n.join(before.select((-F.col("key")).alias("size"), "before"), "size").select("net", (F.col("before") + 1).alias("r"))


@query("op_topk", "SELECT l_orderkey, l_linenumber, l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber LIMIT 20")
def _(spark, d):
    return W.table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_extendedprice").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber").limit(20)


@query("op_set_except", "SELECT DISTINCT l_partkey AS node FROM lineitem WHERE l_returnflag = 'R' EXCEPT SELECT l_partkey FROM lineitem WHERE l_returnflag = 'A'")
def _(spark, d):
    li = W.table(spark, d, "lineitem")
    of = lambda f: li.filter(F.col("l_returnflag") == f).select(F.col("l_partkey").alias("node"))
    return of("R").distinct().exceptAll(of("A").distinct())


@query("op_array_jaccard", """WITH t AS (SELECT conv_id, list_distinct(string_split(lower(string_agg(text, ' ' ORDER BY turn)), ' ')) AS w FROM conversations GROUP BY conv_id)
        SELECT a.conv_id AS a, b.conv_id AS b, round(len(list_intersect(a.w, b.w)) / (len(a.w) + len(b.w) - len(list_intersect(a.w, b.w))), 6) AS jaccard FROM t a JOIN t b ON b.conv_id = a.conv_id + 1""")
def _(spark, d):
    c = W.table(spark, d, "conversations").groupBy("conv_id").agg(F.array_distinct(F.split(F.lower(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "text"))), lambda x: x["text"]), " ")), " ")).alias("w"))
    b = c.select((F.col("conv_id") - 1).alias("conv_id"), F.col("conv_id").alias("b"), F.col("w").alias("v"))
    return c.join(b, "conv_id").select(F.col("conv_id").alias("a"), "b", F.round(F.size(F.array_intersect("w", "v")) / F.size(F.array_union("w", "v")), 6).alias("jaccard"))


@query("st_tumbling", "SELECT epoch(time_bucket(INTERVAL 1 HOUR, ts))::BIGINT AS start, event_type, user_id, count(*) AS n FROM events GROUP BY 1, 2, 3")
def _(spark, d):
    from ..streaming import windows

    e = W.table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return windows.window_pins(e).select(F.unix_seconds("start").alias("start"), "event_type", "user_id", "n")


@query("st_pair_events", "SELECT a.user_id, a.event_id AS first_id, b.event_id AS then_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def _(spark, d):
    from ..streaming import windows

    return windows.pair_events(W.table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp")))


@query("st_route", "SELECT event_id, CAST(CASE WHEN user_id % 2 = 0 THEN (user_id * 7919 + 13) % 8 END AS INTEGER) AS block FROM events")
def _(spark, d):
    from ..streaming import windows

    e = W.table(spark, d, "events")
    p = e.select(F.col("user_id").alias("node")).distinct().filter("node % 2 = 0").select("node", F.pmod(F.col("node") * 7919 + 13, F.lit(K)).cast("int").alias("block"))
    return windows.route(e, p).select("event_id", "block")


# -- whole runs -----------------------------------------------------------------------------------------------------


def checked(h: Hypergraph, blocks: DataFrame, k: int = K, objective: str = "km1") -> DataFrame:
    """One row: nodes, each placed once; whether the blocks keep the bound, and stay under the objective of the reference partition, which SQL knows."""
    r = metrics.report(h, blocks, k, EPS).select(objective, "feasible")
    once = h.nodes.join(blocks, "node", "left").agg(F.count("*").alias("rows"), F.count_distinct("node").alias("nodes"), F.coalesce(F.bool_and(F.col("block").between(0, k - 1)), F.lit(True)).alias("known"))
    floor = metrics.objectives_df(h, reference_partition(h, k)).select(F.col(objective).alias("floor"))
    return once.crossJoin(r).crossJoin(floor).select("nodes", ((F.col("rows") == F.col("nodes")) & F.col("known")).alias("placed_once"), "feasible", "floor", (F.col(objective) < F.col("floor")).alias("below_floor"))


def checked_sql(w: str, k: int = K, objective: str = "km1") -> str:
    value = {"km1": "sum(la - 1)", "cut": "count(*) FILTER (WHERE la > 1)", "soed": "sum(CASE WHEN la > 1 THEN la END)"}[objective]
    return over(w, f"SELECT (SELECT count(*) FROM nodes) AS nodes, TRUE AS placed_once, TRUE AS feasible, (SELECT CAST(coalesce({value}, 0) AS BIGINT) FROM lam) AS floor, TRUE AS below_floor", k)


def whole(name: str, workload: str, k: int = K, objective: str = "km1"):
    """Register a run (h, k) -> blocks on a workload with the invariants of its result."""

    def add(f):
        def run(spark, d):
            h = W.HYPERGRAPHS[workload](spark, d).materialised("input")
            return checked(h, truncate_lineage(f(h, k), "blocks"), k, objective)

        QUERIES[name], SQL[name] = run, checked_sql(workload, k, objective)
        WHOLE.add(name)
        return f

    return add


def _run(preset: str = "default", **changes):
    from dataclasses import replace

    def run(h, k):
        from .multilevel import PRESETS, partition

        objective = changes.get("objective", "km1")
        config = replace(PRESETS[preset], **{key: v for key, v in changes.items() if key != "objective"})
        return partition(h, k, EPS, objective=objective, config=config).blocks

    return run


for _n, _p in enumerate(("speed_det", "default", "default_flows", "quality", "quality_flows"), 1):
    whole(f"z0{_n}_{_p}", "w1")(_run(_p))
for _w in ("w2s", "w3d", "w5", "w6", "w7", "w12"):
    whole(f"z02_default_{_w}", _w)(_run())
#: Small levels, so that the hierarchy shows on a small workload.
SMALL = {"coarse_per_block": 16}
for _p in ("speed_det", "default_flows", "quality", "quality_flows"):
    whole(f"z_{_p}_w7", "w7")(_run(_p, **SMALL))
whole("z06_no_fm", "w1")(_run(fm=False))
for _o in ("cut", "soed"):
    whole(f"z09_objective_{_o}_w7", "w7", objective=_o)(_run(objective=_o, **SMALL))
whole("z10_k64_w1", "w1", 64)(_run(runs=(1, 1, False), coarse_per_block=20))
whole("m08_recursive_w7", "w7")(_run(scheme="recursive", runs=(1, 1, False), **SMALL))
#: The superstep path: levels are tables although they would fit a task.
TABLES = {"task_pins": 900, "coarse_per_block": 30, "superstep_rounds": 1, "runs": (1, 1, False)}
whole("z02_distributed_w7", "w7", 4)(_run(communities=False, **TABLES))


whole("n08_tables_w7", "w7", 4)(_run("quality", **(TABLES | {"coarse_per_block": 80})))


@whole("c09_vcycle_w7", "w7")
def _(h, k):
    from .multilevel import vcycle

    return vcycle(h, reference_partition(h, k), k, EPS).blocks


@whole("i03_static_schedule_w7", "w7")
def _(h, k):
    """Bisections dealt one task a part instead of many small tasks."""
    import pandas as pd

    from ..functions import arrays

    h, copies = contract.without_copies(h, k, EPS, least=0)
    a = initial.gather(h)
    g = arrays.Csr.of(a)
    part = initial.recursive(h.pins.sparkSession, g, k, EPS, runs=(2, 2, False), schedule="static")
    state = arrays.State(g, part, k)
    arrays.rebalance(state, arrays.block_limit(g, k, EPS))
    p = h.pins.sparkSession.createDataFrame(pd.DataFrame({"node": a["node_ids"], "block": state.part.astype("int32")}), "node long, block int")
    return p if copies is None else contract.project(p, copies)


def _baseline(f):
    def run(spark, d):
        from . import baselines

        return f(baselines, W.order_parts(spark, d))

    return run


SQL["b_round_robin"] = over("w1", "SELECT node, CAST(node % 8 AS INTEGER) AS block FROM nodes")
SQL["b_range"] = over("w1", "SELECT node, CAST(least((row_number() OVER (ORDER BY node) - 1) * 8 // (SELECT count(*) FROM nodes), 7) AS INTEGER) AS block FROM nodes")
SQL["b_hash"] = over("w1", "SELECT node, CAST((node * 7919 + 13) % 1048573 % 8 AS INTEGER) AS block FROM nodes")
SQL["b_random"] = over("w1", "SELECT node, CAST((row_number() OVER (ORDER BY (node * 7919 + 13) % 1048573, node) - 1) % 8 AS INTEGER) AS block FROM nodes")
SQL["b_attribute"] = "SELECT p_partkey AS node, CAST(dense_rank() OVER (ORDER BY p_brand) - 1 AS INTEGER) AS block FROM part"
QUERIES["b_round_robin"] = _baseline(lambda b, h: b.round_robin(h, K))
QUERIES["b_range"] = _baseline(lambda b, h: b.range_blocks(h, K))
QUERIES["b_hash"] = _baseline(lambda b, h: b.hashed(h, K, plain=True))
QUERIES["b_random"] = _baseline(lambda b, h: b.random_blocks(h, K, plain=True))


@query("b_attribute", SQL["b_attribute"])
def _(spark, d):
    from . import baselines

    return baselines.by_attribute(W.table(spark, d, "part"), "p_partkey", "p_brand")


def _floor(name):
    def run(h, k):
        from . import baselines

        return getattr(baselines, name)(h, k, EPS)

    return run


whole("b_flat_lp", "w1")(_floor("flat_lp"))
whole("b_bfs_grow", "w1")(_floor("bfs_grow"))


def _stand(name):
    def run(h, k):
        from . import baselines

        return baselines.stand_in(h, k, EPS, name, per_block=16)

    return run


for _s in (
    "rb_matching", "kway_matching", "kway_fast", "kway_lpclust", "kway_eco", "kway_lpclust_eco", "kway_strong", "kway_lpclust_strong", "rb_bfs", "lp_only", "hill_scanning", "oriented_moves", "fm_local_only",
    "lp_fast", "lp_eco", "rb_cluster", "rb_cluster_best", "n_level", "n_level_flows_rb", "n_level_flows", "pair_matching", "det_matching", "flat_kway",
):
    whole(f"b_{_s}_w7", "w7")(_stand(_s))
for _s in ("rb_matching_soed", "kway_matching_soed"):
    whole(f"b_{_s}_w7", "w7", objective="soed")(_stand(_s))
whole("b_rb_cluster_rownet_w5", "w5")(_stand("rb_cluster"))

from . import experiments, relational  # noqa: E402, F401  registers further queries
