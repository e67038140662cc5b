"""Experiment statistics over a table of runs: (instance, algo, seed, threads, quality, seconds, status)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Seconds that a timed-out run counts with.
LIMIT = 400


def quality(runs: DataFrame) -> DataFrame:
    """(instance, algo, quality): arithmetic mean over the runs that ended well, null if none did."""
    ok = F.when(F.col("status") == "ok", F.col("quality"))
    return runs.groupBy("instance", "algo").agg(F.round(F.avg(ok), 6).alias("quality"))


def times(runs: DataFrame, limit: int = LIMIT) -> DataFrame:
    """(algo, gmean): geometric mean over instances of the mean seconds; timeouts enter with the limit, unbalanced runs as they are."""
    s = F.when(F.col("status") == "timeout", F.lit(limit)).otherwise(F.least(F.col("seconds"), F.lit(limit)))
    mean = runs.groupBy("instance", "algo").agg(F.avg(s).alias("t"))
    return mean.groupBy("algo").agg(F.round(F.exp(F.avg(F.log("t"))), 6).alias("gmean"))


def slowdown(runs: DataFrame, a: int, b: int, limit: int = LIMIT) -> DataFrame:
    """One row: how many times the geometric mean time of ``a`` is that of ``b``, on instances that both ran."""
    s = F.when(F.col("status") == "timeout", F.lit(limit)).otherwise(F.least(F.col("seconds"), F.lit(limit)))
    mean = runs.groupBy("instance", "algo").agg(F.avg(s).alias("t"))
    x, y = mean.filter(F.col("algo") == a).select("instance", F.col("t").alias("ta")), mean.filter(F.col("algo") == b).select("instance", F.col("t").alias("tb"))
    return x.join(y, "instance").agg(F.round(F.exp(F.avg(F.log(F.col("ta") / F.col("tb")))), 6).alias("ratio"), F.count("*").alias("instances"))


def pareto(runs: DataFrame) -> DataFrame:
    """(algo, quality, seconds, front): harmonic means of the ratios to the best of each instance; front if none is at least as good in both and better in one."""
    q = runs.filter("status = 'ok'").groupBy("instance", "algo").agg(F.avg("quality").alias("q"), F.avg("seconds").alias("t"))
    w = Window.partitionBy("instance")
    r = q.select("algo", (F.min("q").over(w) / F.col("q")).alias("iq"), (F.min("t").over(w) / F.col("t")).alias("it"))
    p = r.groupBy("algo").agg(F.round(F.count("*") / F.sum("iq"), 6).alias("quality"), F.round(F.count("*") / F.sum("it"), 6).alias("seconds"))
    o = p.select(F.col("quality").alias("q2"), F.col("seconds").alias("s2"))
    beaten = p.join(F.broadcast(o), (F.col("q2") <= F.col("quality")) & (F.col("s2") <= F.col("seconds")) & ((F.col("q2") < F.col("quality")) | (F.col("s2") < F.col("seconds"))), "left_semi").select("algo", F.lit(True).alias("beaten"))
    return p.join(beaten, "algo", "left").select("algo", "quality", "seconds", F.col("beaten").isNull().alias("front"))


def profile(runs: DataFrame, taus: list[float]) -> DataFrame:
    """(algo, tau, share): instances on which an algorithm is within tau times the best; those without a good run count as not."""
    spark = runs.sparkSession
    q = quality(runs)
    best = F.min("quality").over(Window.partitionBy("instance"))
    grid = spark.createDataFrame([(float(t),) for t in taus], "tau double")
    x = q.withColumn("best", best).crossJoin(F.broadcast(grid))
    return x.groupBy("algo", "tau").agg(F.round(F.avg(F.when(F.col("quality") <= F.col("tau") * F.col("best"), 1.0).otherwise(0.0)), 6).alias("share"))


def infeasible_share(runs: DataFrame, flag: float = 0.15) -> DataFrame:
    """(algo, share, flagged): instances whose runs are all infeasible."""
    x = runs.groupBy("instance", "algo").agg(F.min((F.col("status") == "infeasible").cast("int")).alias("none"))
    s = F.round(F.avg("none"), 6)
    return x.groupBy("algo").agg(s.alias("share"), (s > flag).alias("flagged"))


def _pairs(runs: DataFrame, a: int, b: int) -> DataFrame:
    q = quality(runs).filter("quality is not null")
    return q.filter(F.col("algo") == a).select("instance", F.col("quality").alias("qa")).join(q.filter(F.col("algo") == b).select("instance", F.col("quality").alias("qb")), "instance")


def wilcoxon(runs: DataFrame, a: int, b: int) -> DataFrame:
    """One row (n, w_plus, z, significant): signed ranks of paired qualities, ties averaged, zeros dropped. One row an instance is ranked."""
    d = _pairs(runs, a, b).select((F.col("qa") - F.col("qb")).alias("d")).filter("d <> 0")
    by = Window.orderBy(F.abs("d"))
    same = Window.partitionBy(F.abs("d"))
    r = d.withColumn("rank", F.rank().over(by) + (F.count("*").over(same) - 1) / 2).withColumn("ties", F.count("*").over(same))
    s = r.agg(F.count("*").alias("n"), F.coalesce(F.sum(F.when(F.col("d") > 0, F.col("rank"))), F.lit(0.0)).alias("w"), F.coalesce(F.sum((F.col("ties") * F.col("ties") - 1) / 48.0), F.lit(0.0)).alias("t"))
    n = F.col("n").cast("double")
    z = F.round((F.col("w") - n * (n + 1) / 4) / F.sqrt(n * (n + 1) * (2 * n + 1) / 24 - F.col("t")), 6)
    return s.select("n", F.round("w", 6).alias("w_plus"), z.alias("z"), (F.abs(z) > 2.576).alias("significant"))


def median_improvement(runs: DataFrame, a: int, b: int) -> DataFrame:
    """One row: median over instances of quality(b) / quality(a) - 1 in percent."""
    return _pairs(runs, a, b).agg(F.round((F.percentile(F.col("qb") / F.col("qa"), F.lit(0.5)) - 1) * 100, 6).alias("percent"))


def win_share(runs: DataFrame, a: int, b: int) -> DataFrame:
    return _pairs(runs, a, b).agg(F.round(F.avg((F.col("qa") < F.col("qb")).cast("double")), 6).alias("better"), F.round(F.avg((F.col("qa") == F.col("qb")).cast("double")), 6).alias("equal"))


def effectiveness(runs: DataFrame, a: int, b: int, draws: int = 10) -> DataFrame:
    """(instance, draw, qa, qb): virtual instances of equal expected time.

    In each, both draw runs in a hash order of (seed, draw). The side with the faster first run goes on until its time passes the other's first
    run; the run that passes counts with the probability (time left) / (its time). The value is the least quality that counts.
    """
    spark = runs.sparkSession
    ok = runs.filter((F.col("status") == "ok") & F.col("algo").isin(a, b))
    x = ok.crossJoin(F.broadcast(spark.range(draws).withColumnRenamed("id", "draw")))
    h = F.pmod(F.col("seed") * 7919 + F.col("draw") * 104729 + F.col("algo") * 31, F.lit(65537))
    w = Window.partitionBy("instance", "algo", "draw").orderBy("h", "seed")
    x = x.withColumn("h", h).withColumn("n", F.row_number().over(w)).withColumn("before", F.coalesce(F.sum("seconds").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    first = x.filter("n = 1")
    fa, fb = first.filter(F.col("algo") == a).select("instance", "draw", F.col("seconds").alias("ta")), first.filter(F.col("algo") == b).select("instance", "draw", F.col("seconds").alias("tb"))
    y = x.join(fa.join(fb, ["instance", "draw"]), ["instance", "draw"])
    slow = F.greatest("ta", "tb")
    u = F.pmod(F.col("h") * 31 + 17, F.lit(1000)) / 1000.0
    counts = (F.col("n") == 1) | ((F.col("before") < slow) & ((F.col("before") + F.col("seconds") <= slow) | (u < (slow - F.col("before")) / F.col("seconds"))))
    # only the faster side draws again
    mine = F.when(F.col("algo") == a, F.col("ta") < F.col("tb")).otherwise(F.col("tb") < F.col("ta"))
    z = y.filter(counts & ((F.col("n") == 1) | mine)).groupBy("instance", "draw").agg(F.min(F.when(F.col("algo") == a, F.col("quality"))).alias("qa"), F.min(F.when(F.col("algo") == b, F.col("quality"))).alias("qb"))
    return z.select("instance", "draw", "qa", "qb")


def speedup(runs: DataFrame, threshold: int = 200, above: float = 1.0) -> DataFrame:
    """(threads, gmean, gmean_long, share): single-thread mean seconds over those with more threads, by geometric mean over (instance, algo); long ones and the share above a speedup apart."""
    t = runs.filter("status = 'ok'").groupBy("instance", "algo", "threads").agg(F.avg("seconds").alias("t"))
    one = t.filter("threads = 1").select("instance", "algo", F.col("t").alias("t1"))
    x = t.filter("threads > 1").join(one, ["instance", "algo"]).withColumn("s", F.col("t1") / F.col("t"))
    return x.groupBy("threads").agg(F.round(F.exp(F.avg(F.log("s"))), 6).alias("gmean"), F.round(F.exp(F.avg(F.when(F.col("t1") >= threshold, F.log("s")))), 6).alias("gmean_long"), F.round(F.avg((F.col("s") > above).cast("double")), 6).alias("share"))


def rolling_gmean(points: DataFrame, order: str, value: str, window: int = 25) -> DataFrame:
    """``points`` with the centred rolling geometric mean of ``value`` over ``window`` rows by ``order``. One row an instance."""
    half = window // 2
    return points.withColumn("rolling", F.round(F.exp(F.avg(F.log(value)).over(Window.orderBy(order).rowsBetween(-half, half))), 6))


def component_shares(events: DataFrame) -> DataFrame:
    """(phase, median, at): per phase the median of its share of an instance's seconds, from (instance, phase, seconds), and in how many instances it has any."""
    x = events.groupBy("instance", "phase").agg(F.sum("seconds").alias("s"))
    x = x.withColumn("share", F.col("s") / F.sum("s").over(Window.partitionBy("instance")))
    return x.groupBy("phase").agg(F.round(F.percentile("share", F.lit(0.5)), 6).alias("median"), F.count("*").alias("instances"))


def share_curve(events: DataFrame) -> DataFrame:
    """(phase, share, reached): for each share the part of instances with at least it."""
    x = events.groupBy("instance", "phase").agg(F.sum("seconds").alias("s"))
    x = x.withColumn("share", F.round(F.col("s") / F.sum("s").over(Window.partitionBy("instance")), 6))
    w = Window.partitionBy("phase").orderBy(F.desc("share"))
    return x.withColumn("reached", F.round(F.cume_dist().over(w), 6)).select("phase", "share", "reached").distinct()


def gain_mismatch(log: DataFrame) -> DataFrame:
    """One row: share of rows (expected, attributed) that differ, and of those that turned out negative."""
    return log.agg(F.count("*").alias("n"), F.round(F.avg((F.col("expected") != F.col("attributed")).cast("double")), 6).alias("mismatch"), F.round(F.avg((F.col("attributed") < 0).cast("double")), 6).alias("negative"))


def rollup_quality(runs: DataFrame) -> DataFrame:
    return runs.rollup("algo", "status").agg(F.count("*").alias("n"), F.sum("quality").cast("long").alias("quality"), F.grouping_id().cast("long").alias("level"))


def cube_quality(runs: DataFrame) -> DataFrame:
    return runs.cube("algo", "threads").agg(F.count("*").alias("n"), F.sum("seconds").cast("long").alias("seconds"), F.grouping_id().cast("long").alias("level"))


def pivot_quality(runs: DataFrame) -> DataFrame:
    x = runs.groupBy("algo").pivot("threads", [1, 4, 16]).agg(F.sum("quality").cast("long"))
    return x.select("algo", F.col("1").alias("t1"), F.col("4").alias("t4"), F.col("16").alias("t16"))
