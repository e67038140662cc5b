"""Mixing sources to target weights by entropy balancing."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators.prefix import dense_ids
from .common import as_bytes, bounded_broadcast, column_stretches, small_batches, tidy, written

SLOTS = 32
#: Size classes to an octave.
PER_OCTAVE = 4
#: Constraints (values of all dimensions together) whose dense Hessian the driver solves, where dimensions overlap.
MAX_CONSTRAINTS = 4_000


def word_counts(batches):
    """Number of runs of bytes outside 0x20 and 0x09-0x0D."""
    for batch in batches:
        sizes = [len(t.split()) for _, part in column_stretches(batch.column("body")) for t in part]
        yield pa.RecordBatch.from_arrays([*(batch.column(n) for n in batch.schema.names if n != "body"), pa.array(sizes, pa.int64())], [*(n for n in batch.schema.names if n != "body"), "size"])


def capped_unit(rows: DataFrame, most: float) -> float:
    """The unit by which ``rows`` (source_size, weight) share all sizes: a target is weight * unit, or ``most`` times its size if that is less.

    Each round is one aggregation: what the sources over their cap leave is shared among the others. Caps only ever grow in number, so rounds end.
    """
    total, unit, capped_before = None, 0.0, -1
    while True:
        over = F.col("weight") * F.lit(unit) > F.col("source_size") * F.lit(float(most))
        open_ = (F.col("source_size") > 0) & ~over
        held, weight, capped, everything = rows.agg(F.coalesce(F.sum(F.when(over, F.col("source_size"))), F.lit(0)), F.coalesce(F.sum(F.when(open_, F.col("weight"))), F.lit(0.0)), F.count_if(over), F.coalesce(F.sum("source_size"), F.lit(0))).first()
        total = everything if total is None else total
        if not weight or capped == capped_before:
            return unit
        unit, capped_before = (total - most * held) / weight, capped


def newton(cells: DataFrame, dims: list[str], targets: DataFrame, rounds: int = 60, tol: float = 1e-9) -> DataFrame:
    """Multipliers of the dual: (dim, value, multiplier) for constraints that may overlap.

    ``cells``: one column a dimension and ``tokens``; ``targets``: (dim, value, target). The dual
    sum tokens * exp(sum of multipliers) - sum multiplier * target is convex; its gradient (mass of each constraint less its target) and Hessian
    (mass that two constraints share) are sums that Spark aggregates over the cells in every step; the driver solves the system,
    of at most MAX_CONSTRAINTS rows, in the least squares sense (dimensions share a direction: all masses together),
    and halves a step until the dual falls.
    """
    spark = cells.sparkSession
    goal = {(r["dim"], r["value"]): float(r["target"]) for r in targets.collect()} if targets.count() <= MAX_CONSTRAINTS else None
    if goal is None:
        raise ValueError(f"overlapping constraints take up to {MAX_CONSTRAINTS} values")
    names = sorted(k for k, t in goal.items() if t > 0)
    place = {k: i for i, k in enumerate(names)}
    lam, wanted = np.zeros(len(names)), np.array([goal[k] for k in names])
    for d in dims:
        empty = [v for dim, v in goal if dim == d and goal[dim, v] <= 0]
        cells = cells.filter(~F.col(d).isin(*empty)) if empty else cells
    cells = written(cells, "cells")

    def mass_of(at: np.ndarray) -> DataFrame:
        out, total = cells, F.lit(0.0)
        for i, d in enumerate(dims):
            own = spark.createDataFrame([(v, float(at[place[dim, v]])) for dim, v in names if dim == d], f"{d} string, _m{i} double")
            out, total = out.join(F.broadcast(own), d), total + F.col(f"_m{i}")
        return out.withColumn("mass", F.col("tokens") * F.exp(total))

    def dual(at: np.ndarray) -> float:
        return float(mass_of(at).agg(F.coalesce(F.sum("mass"), F.lit(0.0))).first()[0]) - float(at @ wanted)

    value = dual(lam)
    for _ in range(rounds):
        mass = mass_of(lam)
        member = F.array(*[F.struct(F.lit(d).alias("dim"), F.col(d).alias("value")) for d in dims])
        pairs = mass.select("mass", F.explode(member).alias("a"), member.alias("all")).select("mass", "a", F.explode("all").alias("b"))
        hessian = np.zeros((len(names), len(names)))
        for r in pairs.groupBy("a", "b").agg(F.sum("mass").alias("m")).collect():
            hessian[place[tuple(r["a"])], place[tuple(r["b"])]] = r["m"]
        gradient = hessian.diagonal() - wanted
        if not len(names) or np.abs(gradient).max() <= tol * max(1.0, wanted.max()):
            break
        step = np.linalg.lstsq(hessian, gradient, rcond=1e-12)[0]
        scale = 1.0
        while scale > 1e-6 and (after := dual(lam - scale * step)) > value:
            scale /= 2
        if scale <= 1e-6:
            break
        lam, value = lam - scale * step, after
    return spark.createDataFrame([(d, v, float(lam[place[d, v]])) for d, v in names], "dim string, value string, multiplier double")


def diagonal_tilt(sizes: DataFrame, rounds: int = 60, tol: float = 1e-9) -> DataFrame:
    """Newton on the dual where constraints share no cell, so its Hessian is diagonal and each source is solved where it lies.

    ``sizes``: (source, source_size, target). Adds ``rate`` = exp(multiplier), 0 where either is 0.
    The multiplier starts above its solution, from where Newton on a convex function
    descends monotonically.
    """

    def solve(batches):
        for pdf in batches:
            size, target = pdf["source_size"].to_numpy(float), pdf["target"].to_numpy(float)
            on = (size > 0) & (target > 0)
            lam = np.zeros(len(pdf))
            lam[on] = np.maximum(0.0, np.ceil(np.log2(target[on] / size[on]) * np.log(2)) + 1)
            for _ in range(rounds):
                mass = size * np.exp(lam)
                step = np.where(on, (mass - target) / np.where(on, mass, 1.0), 0.0)
                lam -= step
                if np.abs(step).max(initial=0.0) <= tol:
                    break
            yield pdf.assign(rate=np.where(on, np.exp(lam), 0.0))

    return sizes.mapInPandas(tidy(solve), ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in sizes.schema) + ", rate double")


def _pick_cells(pdf: pd.DataFrame) -> pd.DataFrame:
    """Cells of one source, largest sizes first: each takes one extra copy if that brings the running total nearer to its course."""
    pdf = pdf.sort_values(["bin", "slot"], ascending=[False, True], kind="stable")
    tokens, part = pdf["tokens"].to_numpy(float), float(pdf["rate"].iloc[0]) % 1.0
    extra, due, taken = np.zeros(len(pdf), bool), 0.0, 0.0
    for i, size in enumerate(tokens):
        due += size * part
        if abs(taken + size - due) <= abs(taken - due):
            extra[i], taken = True, taken + size
    return pdf.assign(extra=extra)[["group", "bin", "slot", "extra"]]


def _key(column: Column) -> Column:
    """Sources in order: by code point (of UTF-8 bytes, which is the same), null last."""
    return F.struct(column.isNull().alias("none"), F.coalesce(column.cast("string"), F.lit("")).alias("name"))


def source_targets(sums: DataFrame, weights: tuple[float, ...], most: float) -> DataFrame:
    """(group, source_size, target) from (group, source_size): weights in turn over the sorted groups, capped at ``most`` times a size."""
    ids = dense_ids(sums, "group")
    nth = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.col("id") % len(weights) + 1).cast("int"))
    rows = written(sums.join(ids, "group").select("group", "source_size", nth.alias("weight")), "sources")
    unit = capped_unit(rows, most)
    target = F.when(F.col("source_size") > 0, F.least(F.col("weight") * F.lit(unit), F.col("source_size") * F.lit(float(most)))).otherwise(0.0)
    return rows.select("group", "source_size", target.alias("target"))


def mix_sources(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: tuple[float, ...] = (5, 2, 1), most: float = 3.0, carry: tuple[str, ...] = (), also: tuple[str, ...] = ()) -> DataFrame:
    """One row per document: id, size, source_size, target, taken, copies, rate.

    Sources sorted by code point (null last) get ``weights`` in turn; the
    targets share all tokens by weight, capped at ``most`` times a source's
    own. Document rates minimise the token-weighted relative entropy to the
    present corpus under those token constraints; the dual is solved by Newton
    steps on sums that Spark aggregates. Sources alone share no document, so each is solved where its row lies, however many there
    are. ``also`` names further columns whose values get targets by the same rule: those constraints overlap with the sources', and
    each Newton step sums gradient and Hessian over the cells of the corpus (``newton``). A rate exp(lambda) becomes floor(rate) copies, and one more for whole
    cells (group of equal rate, size class, hash slot of the id) picked from the largest
    sizes down so that the group's total follows its course; no document gets more than
    ceil(rate) copies, at most ceil(most) with sources alone. The cells of a group are bounded in number, whatever its size, and reruns agree.

    Null texts have size 0 and take 0. Null sources form one source. Repeated rows are
    documents of their own and get equal copies. An empty table gives an empty result.
    ``carry`` names further columns to keep; those named like a result column give way to it.
    """
    small_batches(docs.sparkSession)
    results = ("size", "source_size", "target", "taken", "copies", "rate")
    carry = tuple(c for c in carry if c not in results)
    kind = {f.name: f.dataType.simpleString() for f in docs.schema}
    columns = list(dict.fromkeys([id_col, source_col, *also, *carry]))
    rows = docs.select(*[F.col(c).alias(f"c{i}") for i, c in enumerate(columns)], as_bytes(text_col).alias("body"))
    rows = rows.mapInArrow(tidy(word_counts), ", ".join(f"c{i} {kind[c]}" for i, c in enumerate(columns)) + ", size long")
    own = {c: _key(F.col(f"c{columns.index(c)}")) for c in (source_col, *also)}
    rows = rows.withColumn("bin", F.when(F.col("size") > 0, F.floor(F.log2(F.col("size").cast("double")) * PER_OCTAVE)).otherwise(-1).cast("int")).withColumn("slot", F.pmod(F.xxhash64("c0"), F.lit(SLOTS)).cast("int"))
    rows = written(rows.withColumn("source", own[source_col]).withColumn("group", F.to_json(F.struct(*own.values())) if also else F.col("source")), "sizes")
    sums = written(rows.groupBy(F.col("source").alias("group")).agg(F.sum("size").cast("long").alias("source_size")), "sums")
    targets = written(source_targets(sums, weights, most), "targets")
    n = targets.count()
    if also:
        table = _overlapping(rows, {c: own[c] for c in also}, targets, weights, most)
    else:
        table = diagonal_tilt(targets).select("group", F.col("group").alias("source"), "source_size", "target", F.least(F.when(F.abs(F.col("rate") - F.round("rate")) < 1e-9, F.round("rate")).otherwise(F.col("rate")), F.lit(float(most))).alias("rate"))
    table = written(table, "rates")
    n = table.count() if also else n
    rates = bounded_broadcast(table.select("group", "source_size", "target", "rate"), n, 10_000)
    cells = rows.filter("size > 0").groupBy("group", "bin", "slot").agg(F.sum("size").alias("tokens")).join(rates.select("group", "rate"), "group")
    group_type = rows.schema["group"].dataType.simpleString()
    picked = cells.groupBy("group").applyInPandas(_pick_cells, f"group {group_type}, bin int, slot int, extra boolean")
    picked = written(picked.filter("extra"), "picked")
    out = rows.join(rates, "group").join(bounded_broadcast(picked, picked.count(), 200_000), ["group", "bin", "slot"], "left")
    copies = (F.floor("rate") + F.when(F.col("extra"), 1).otherwise(0)).cast("long")
    return out.select(F.col("c0").alias(id_col), *[F.col(f"c{columns.index(c)}").alias(c) for c in carry if c != id_col], "size", "source_size", "target", (copies * F.col("size")).alias("taken"), copies.alias("copies"), "rate")


def _overlapping(rows: DataFrame, also: dict[str, Column], targets: DataFrame, weights: tuple[float, ...], most: float) -> DataFrame:
    """(group, source, source_size, target, rate) where sources and other columns are constrained together."""
    text = F.to_json("group")
    dims = ["d0", *(f"d{i}" for i in range(1, len(also) + 1))]
    keys = [F.col("source"), *also.values()]
    cells = written(rows.groupBy("group", "source", *[F.to_json(k).alias(d) for k, d in zip(keys, dims, strict=True)]).agg(F.sum("size").cast("long").alias("tokens")), "joint")
    all_targets = targets.select(F.lit("d0").alias("dim"), text.alias("value"), "target")
    for k, d in zip(list(also.values()), dims[1:], strict=True):
        sums = written(rows.groupBy(k.alias("group")).agg(F.sum("size").cast("long").alias("source_size")), "sums")
        all_targets = all_targets.union(source_targets(sums, weights, most).select(F.lit(d), text, "target"))
    found = newton(cells.select(*dims, "tokens"), dims, written(all_targets, "goals"))
    out, total = cells, F.lit(0.0)
    for d in dims:
        own = found.filter(F.col("dim") == d).select(F.col("value").alias(d), F.col("multiplier").alias(f"{d}_m"))
        out, total = out.join(F.broadcast(own), d, "left"), total + F.col(f"{d}_m")
    return out.join(targets.select(F.col("group").alias("source"), "source_size", "target"), "source").select("group", "source", "source_size", "target", F.coalesce(F.exp(total), F.lit(0.0)).alias("rate"))
