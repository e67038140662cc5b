"""Streams against their batch twins."""

import pandas as pd
from pyspark.sql import functions as F

from hgpart.functions import udfs
from hgpart.model import build
from hgpart.operators import metrics
from hgpart.sources import workloads
from hgpart.streaming import online, windows

SF = "/root/testdata/sf0.001"


def drain(stream, name, mode, spark, tmp_path):
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


def test_window_pins_match_batch(spark, tmp_path):
    events = spark.read.parquet(f"{SF}/events.parquet")
    events.repartition(3).write.parquet(str(tmp_path / "in"))
    stream = windows.event_stream(spark, str(tmp_path / "in"))
    batch = events.withColumn("ts", F.col("ts").cast("timestamp"))
    for kind, extra in (("tumbling", {}), ("sliding", {"slide": "30 minutes"})):
        got = drain(windows.window_pins(stream, kind, watermark=None, **extra), f"w_{kind}", "complete", spark, tmp_path)
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, windows.window_pins(batch, kind, **extra).collect()))
    assert windows.window_pins(batch, "session", "10 minutes").count() > 0
    doubled = batch.union(batch)
    assert windows.deduplicated(doubled).count() == batch.count()


def test_online_assignment(spark, tmp_path):
    pins = workloads.order_parts(spark, SF).pins
    pins.repartition(2).write.parquet(str(tmp_path / "pins"))
    stream = spark.readStream.schema("net long, node long").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "pins"))
    got = drain(online.online_assign(stream, 4, shards=2), "placed", "append", spark, tmp_path)
    assert got.count() == got.select("node").distinct().count() == pins.select("node").distinct().count()
    loads = [r["count"] for r in got.groupBy("block").count().collect()]
    assert max(loads) <= 1.25 * sum(loads) / 4 + 4
    assert {r["block"] for r in got.select("block").distinct().collect()} == {0, 1, 2, 3}


def test_batches_are_idempotent(spark, tmp_path):
    h = build(spark.createDataFrame([(0, 0), (0, 1), (1, 2), (1, 3), (2, 0), (2, 2)], "net long, node long"))
    run = online.refine_batch(h, 2, 0.5, str(tmp_path / "out"))
    nodes = h.nodes.select("node")
    run(nodes, 0)
    run(nodes, 1)
    first = sorted(map(tuple, spark.read.parquet(str(tmp_path / "out/batch=1")).collect()))
    run(nodes, 1)
    p = spark.read.parquet(str(tmp_path / "out/batch=1"))
    assert sorted(map(tuple, p.collect())) == first and metrics.km1(h, p) <= 3


def test_sql_functions(spark):
    udfs.register(spark)
    x = spark.sql("SELECT hg_adaptive_eps(100D, 4L, 100D, 4L, 0.03D) AS e").first()["e"]
    assert abs(x - (1.03**0.5 - 1)) < 1e-12
    assert [r["node"] for r in spark.sql("SELECT * FROM hg_pins_of_line('3 1 2')").collect()] == [3, 1, 2]
    spark.createDataFrame(pd.DataFrame({"a": [1.0, 2.0], "b": [2.0, 3.0]})).createOrReplaceTempView("q")
    assert abs(spark.sql("SELECT hg_median_improvement(a, b) AS m FROM q").first()["m"] - 75) < 1e-9
    h = workloads.order_parts(spark, SF)
    udfs.register_views(h)
    assert spark.sql("SELECT count(*) AS n FROM pins JOIN nets USING (net)").first()["n"] == h.pins.count()
