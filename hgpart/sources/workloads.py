"""Hypergraphs and graphs of the experiment workloads, built from the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import Hypergraph, build, to_pinlists


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _ids(pairs: DataFrame, key: str) -> DataFrame:
    """Integer nets for text keys: dense rank in binary order, counted by range so that no task ranks all keys."""
    from ..operators.prefix import dense_ids
    from .store import truncate_lineage

    # the texts are read once, not again for the ids and for every table of the hypergraph
    pairs = truncate_lineage(pairs, "pairs")
    return truncate_lineage(pairs.join(dense_ids(pairs.select(key), key, "net"), key).select("net", "node"), "pins")


def order_parts(spark, sf_dir) -> Hypergraph:
    """Order -> its parts."""
    return build(table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("net"), F.col("l_partkey").alias("node")))


def order_part_lists(spark, sf_dir) -> DataFrame:
    """(net, nodes): W1 as pin lists, by one shuffle."""
    pins = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").cast("long").alias("net"), F.col("l_partkey").cast("long").alias("node")).filter("net is not null and node is not null")
    return to_pinlists(pins.repartition("net").distinct())


def part_orders(spark, sf_dir) -> Hypergraph:
    """W3d: part -> its orders."""
    return build(table(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("net"), F.col("l_orderkey").alias("node")))


def order_literals(spark, sf_dir) -> Hypergraph:
    """W3l: order -> (part, returned or not)."""
    return build(table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("net"), (F.col("l_partkey") * 2 + (F.col("l_returnflag") == "R").cast("int")).alias("node")))


def supplier_parts(spark, sf_dir) -> Hypergraph:
    """W2s: supplier -> parts."""
    return build(table(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("net"), F.col("l_partkey").alias("node")))


def customer_parts(spark, sf_dir) -> Hypergraph:
    """Customer -> parts of all orders."""
    o = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    li = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    return build(li.join(o, li.l_orderkey == o.o_orderkey).select(F.col("o_custkey").alias("net"), F.col("l_partkey").alias("node")))


def transactions(spark, sf_dir) -> Hypergraph:
    """W4t: order -> the tuples it touches: customer (4 c), part (4 p + 1), supplier (4 s + 2)."""
    o = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("net"), (F.col("o_custkey") * 4).alias("node"))
    li = table(spark, sf_dir, "lineitem")
    p = li.select(F.col("l_orderkey").alias("net"), (F.col("l_partkey") * 4 + 1).alias("node"))
    s = li.select(F.col("l_orderkey").alias("net"), (F.col("l_suppkey") * 4 + 2).alias("node"))
    return build(o.union(p).union(s))


def _doc_tokens(spark, sf_dir) -> DataFrame:
    d = table(spark, sf_dir, "documents").select("doc_id", F.explode(F.array_distinct(F.split(F.lower("text"), "[ \\t\\r\\n]+"))).alias("token")).filter(F.length("token") >= 4)
    df = d.groupBy("token").agg(F.count("*").alias("n")).filter("n between 2 and 50").select("token")
    return d.join(df, "token").select("token", F.col("doc_id").alias("node"))


def document_tokens(spark, sf_dir) -> Hypergraph:
    """Token (at least 4 letters, in 2 to 50 documents) -> documents."""
    return build(_ids(_doc_tokens(spark, sf_dir), "token"))


def token_documents(spark, sf_dir) -> Hypergraph:
    """W2T: document -> its tokens, the transpose of W2."""
    h = document_tokens(spark, sf_dir)
    return build(h.pins.select(F.col("node").alias("net"), F.col("net").alias("node")))


def page_links(spark, sf_dir) -> Hypergraph:
    """Link target -> pages."""
    p = table(spark, sf_dir, "pages").select(F.col("page_id").alias("node"), F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), 1))).alias("href"))
    return build(_ids(p, "href"))


TYPES = ("click", "error", "purchase", "signup", "view")


def event_windows(spark, sf_dir) -> Hypergraph:
    """(hour, event type) -> users."""
    e = table(spark, sf_dir, "events")
    kind = F.array_position(F.array(*[F.lit(t) for t in TYPES]), F.col("event_type")) - 1
    hour = F.floor(F.unix_seconds(F.col("ts").cast("timestamp")) / 3600)
    return build(e.select((hour * 5 + kind).alias("net"), F.col("user_id").alias("node")))


def shared_lines(spark, sf_dir) -> Hypergraph:
    """Line of at least 20 characters in several documents -> documents."""
    d = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("node"), F.explode(F.array_distinct(F.split("text", "\n"))).alias("line")).filter(F.length("line") >= 20)
    often = d.groupBy("line").agg(F.count("*").alias("n")).filter("n > 1").select("line")
    return build(_ids(d.join(often, "line").select("line", "node"), "line"))


def conversation_tokens(spark, sf_dir) -> Hypergraph:
    """Token in at least two conversations -> conversations."""
    c = table(spark, sf_dir, "conversations").select(F.col("conv_id").alias("node"), F.explode(F.split(F.lower("text"), " ")).alias("token")).filter("token <> ''").distinct()
    often = c.groupBy("token").agg(F.count("*").alias("n")).filter("n > 1").select("token")
    return build(_ids(c.join(often, "token").select("token", "node"), "token"))


def weighted_order_parts(spark, sf_dir) -> Hypergraph:
    """W1 with node weight = part size + 1 and net weight = number of lines."""
    li = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("net"), F.col("l_partkey").alias("node"))
    nodes = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("node"), (F.col("p_size") + 1).alias("weight")).join(li.select("node").distinct(), "node", "left_semi")
    return build(li, nodes, li.groupBy("net").agg(F.count("*").alias("weight")))


def nation_trade(spark, sf_dir) -> DataFrame:
    """(src, dst, weight), lines sold between two nations."""
    li = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    o, c, s = (table(spark, sf_dir, t) for t in ("orders", "customer", "supplier"))
    x = li.join(o, li.l_orderkey == o.o_orderkey).join(c, F.col("o_custkey") == F.col("c_custkey")).join(s, F.col("l_suppkey") == F.col("s_suppkey"))
    x = x.select(F.col("c_nationkey").cast("long").alias("a"), F.col("s_nationkey").cast("long").alias("b")).filter("a <> b")
    return x.groupBy(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).agg(F.count("*").alias("weight"))


def benchmark_passages(spark, sf_dir) -> Hypergraph:
    """Benchmark item -> documents that hold its first eight words, a few giant nets."""
    head = table(spark, sf_dir, "benchmark").select(F.col("item_id").alias("net"), F.array_join(F.slice(F.split(F.lower("text"), "[^a-z]+"), 1, 8), " ").alias("w"))
    d = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("node"), F.split(F.lower("text"), "[^a-z]+").alias("w"))
    d = d.select("node", F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.size("w") - 7, F.lit(1))), lambda i: F.array_join(F.slice("w", i, 8), " ")))).alias("w"))
    return build(d.join(head, "w").select("net", "node"))


def cooccurrence(pins: DataFrame, max_net_size: int | None = None) -> DataFrame:
    """(src, dst, weight): pairs of nodes by the number of nets they share; nets over ``max_net_size`` are left out if given."""
    lists = pins.groupBy("net").agg(F.array_sort(F.collect_list("node")).alias("v"))
    if max_net_size is not None:
        lists = lists.filter(F.size("v") <= max_net_size)
    a = lists.select("v", F.posexplode("v").alias("i", "src"))
    pairs = a.select("src", F.explode(F.slice("v", F.col("i") + 2, F.size("v"))).alias("dst"))
    return pairs.groupBy("src", "dst").agg(F.count("*").alias("weight"))


def cooccurrence_classes(pins: DataFrame) -> DataFrame:
    """(src, dst, weight, member): ``cooccurrence`` without repeating copies. Nodes with the same nets are one class, which its smallest node represents.

    Rows with ``member`` name a representative and another node of its class, which share all their nets; the others are the pairs of representatives. So any two nodes
    share what their representatives do, and nothing is left out.
    """
    from .store import truncate_lineage

    lists = pins.groupBy("node").agg(F.array_sort(F.collect_list("net")).alias("v"))
    first = lists.groupBy("v").agg(F.min("node").alias("rep"), F.collect_list("node").alias("nodes"))
    first = truncate_lineage(first.select("rep", "nodes", "v"), "classes")
    pairs = cooccurrence(first.select(F.explode("v").alias("net"), F.col("rep").alias("node")))
    members = first.select("rep", F.explode("nodes").alias("node"), F.size("v").cast("long").alias("weight")).filter("rep <> node")
    return pairs.withColumn("member", F.lit(False)).union(members.withColumn("member", F.lit(True)))


def co_purchases(spark, sf_dir) -> DataFrame:
    """Parts by common orders."""
    return cooccurrence(order_parts(spark, sf_dir).pins)


def random_hypergraph(spark: SparkSession, n: int, m: int, size: int = 4, seed: int = 0) -> Hypergraph:
    """``m`` nets of up to ``size`` nodes by hash."""
    e = spark.range(m).select(F.col("id").alias("net"), F.explode(F.sequence(F.lit(1), F.lit(size))).alias("j"))
    return build(e.select("net", F.pmod(F.xxhash64("net", "j", F.lit(seed)), F.lit(n)).alias("node")))


def planted(spark: SparkSession, n: int, m: int, k: int, inside: float = 0.9, size: int = 4, seed: int = 0) -> Hypergraph:
    """Nodes v of block v % k; a share ``inside`` of the nets stays in one block, the others spread over all."""
    e = spark.range(m).withColumnRenamed("id", "net")
    u = lambda *c: F.pmod(F.xxhash64(*c, F.lit(seed)), F.lit(1_000_000)) / 1_000_000
    e = e.withColumn("own", u("net", F.lit(-1)) < inside).withColumn("home", F.pmod(F.xxhash64("net", F.lit(-2), F.lit(seed)), F.lit(k)))
    p = e.select("net", "own", "home", F.explode(F.sequence(F.lit(1), F.lit(size))).alias("j"))
    inner = F.pmod(F.xxhash64("net", "j", F.lit(seed)), F.lit(n // k)) * k + F.col("home")
    return build(p.select("net", F.when(F.col("own"), inner).otherwise(F.pmod(F.xxhash64("net", "j", F.lit(seed)), F.lit(n // k * k))).alias("node")))


def embedding_neighbours(spark, sf_dir, k: int = 8) -> DataFrame:
    """Mutual k nearest neighbours by cosine, as edges of weight 1."""
    from ..operators.graphs import knn

    near = knn(table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("v")), k)
    back = near.select(F.col("b").alias("a"), F.col("a").alias("b"))
    return near.join(back, ["a", "b"]).filter("a < b").select(F.col("a").alias("src"), F.col("b").alias("dst"), F.lit(1).cast("long").alias("weight"))


def run_logs(spark, sf_dir) -> DataFrame:
    """A table of runs derived from orders by arithmetic: instance, algo, seed, threads, quality, seconds, status."""
    o = table(spark, sf_dir, "orders")
    return o.select(
        F.pmod("o_custkey", F.lit(50)).alias("instance"),
        F.pmod("o_orderkey", F.lit(4)).alias("algo"),
        F.col("o_orderkey").alias("seed"),
        F.when(F.pmod("o_orderkey", F.lit(3)) == 0, 1).when(F.pmod("o_orderkey", F.lit(3)) == 1, 4).otherwise(16).cast("long").alias("threads"),
        (F.floor(F.col("o_totalprice") / 100) + 1).cast("long").alias("quality"),
        (F.pmod(F.col("o_orderkey") * 37 + F.col("o_custkey"), F.lit(400)) + 1).cast("long").alias("seconds"),
        F.when(F.pmod("o_orderkey", F.lit(29)) == 0, "timeout").when(F.pmod("o_orderkey", F.lit(17)) == 0, "infeasible").otherwise("ok").alias("status"),
    )


HYPERGRAPHS = {
    "w1": order_parts, "w2": document_tokens, "w2t": token_documents, "w2s": supplier_parts, "w3d": part_orders, "w3l": order_literals, "w4": customer_parts, "w4t": transactions,
    "w5": page_links, "w6": event_windows, "w7": shared_lines, "w12": conversation_tokens, "w15": weighted_order_parts, "w17": benchmark_passages,
}
