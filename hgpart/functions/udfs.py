"""Functions for SQL: pins of a line, adaptive imbalance, objectives over views."""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from ..model import Hypergraph


@udtf(returnType="node long")
class PinsOfLine:
    """The node ids of one text line of pins."""

    def eval(self, line: str):
        for x in (line or "").split():
            yield (int(x),)


def register(spark: SparkSession) -> None:
    """``hg_adaptive_eps``, ``hg_median_improvement`` and the table function ``hg_pins_of_line``."""

    def eps(total: pd.Series, k: pd.Series, own: pd.Series, k_own: pd.Series, e: pd.Series) -> pd.Series:
        return pd.Series([((1 + x) * t / a * b / o) ** (1 / math.ceil(math.log2(b))) - 1 if b > 1 else x for t, a, o, b, x in zip(total, k, own, k_own, e, strict=True)])

    def median(a: pd.Series, b: pd.Series) -> float:
        return float(((b / a).median() - 1) * 100) if len(a) else float("nan")

    spark.udf.register("hg_adaptive_eps", F.pandas_udf(eps, "double"))
    median.__annotations__ = {"a": pd.Series, "b": pd.Series, "return": float}
    spark.udf.register("hg_median_improvement", F.pandas_udf(median, "double"))
    spark.udtf.register("hg_pins_of_line", PinsOfLine)


def register_views(h: Hypergraph, p: DataFrame | None = None) -> None:
    """Temporary views nodes, nets, pins and part."""
    h.nodes.createOrReplaceTempView("nodes")
    h.nets.createOrReplaceTempView("nets")
    h.pins.createOrReplaceTempView("pins")
    if p is not None:
        p.createOrReplaceTempView("part")
