"""Online placement of unseen nodes and refinement by micro-batch."""

from __future__ import annotations

from typing import Any

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..model import Hypergraph
from ..operators import refine
from ..sources.store import truncate_lineage


def online_assign(pins: DataFrame, k: int, shards: int = 8) -> DataFrame:
    """(node, block), one row a node, for nodes as they first arrive in a stream of (net, node): the block that most of its nets have, ties to the lighter.

    A node belongs to one shard (hash of its id), which places it once. A shard's state is what it has seen: where its nodes are, in how many of them each net has
    each block, and its loads; so it holds a share of about 1 / ``shards`` and knows nets by its own nodes. A shard keeps its blocks within
    a tenth of each other where it has the choice, hence all do together.
    """

    def place(key: Any, frames, state: GroupState):
        phi, load, where = state.get if state.exists else ([], [0] * k, [])
        counts = {(int(e), int(b)): c for e, b, c in phi}
        home = {int(v): int(b) for v, b in where}
        out = []
        for pdf in frames:
            for v, nets in pdf.groupby("node")["net"]:
                if v not in home:
                    score = [sum(counts.get((int(e), b), 0) for e in nets) for b in range(k)]
                    room = [b for b in range(k) if load[b] <= 1.1 * sum(load) / k + 1]
                    home[int(v)] = max(room, key=lambda b: (score[b], -load[b], -b))
                    load[home[int(v)]] += 1
                    out.append((int(v), home[int(v)]))
                for e in nets:
                    counts[(int(e), home[int(v)])] = counts.get((int(e), home[int(v)]), 0) + 1
        state.update(([(e, b, c) for (e, b), c in counts.items()], list(load), list(home.items())))
        yield pd.DataFrame(out, columns=["node", "block"]).astype({"node": "int64", "block": "int32"})

    dealt = pins.select("net", "node", F.pmod(F.xxhash64("node"), F.lit(shards)).alias("shard"))
    kind = "phi array<struct<e:long,b:int,c:long>>, load array<long>, home array<struct<v:long,b:int>>"
    return dealt.groupBy("shard").applyInPandasWithState(place, "node long, block int", kind, "append", GroupStateTimeout.NoTimeout)


def refine_batch(h: Hypergraph, k: int, eps: float, path: str):
    """A ``foreachBatch`` function: a batch of touched nodes (node) starts label propagation around them and writes the blocks under its id.

    A batch that comes again after a restart overwrites its own folder, so replays change nothing.
    """

    def run(batch: DataFrame, batch_id: int) -> None:
        spark = h.pins.sparkSession
        before = f"{path}/batch={batch_id - 1}"
        p = spark.read.parquet(before) if batch_id else h.nodes.select("node", F.pmod("node", F.lit(k)).cast("int").alias("block"))
        seeds = truncate_lineage(batch.select("node").distinct(), "batch")
        after, _ = refine.lp(h, p, k, eps, rounds=1, seeds=seeds)
        after.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return run
