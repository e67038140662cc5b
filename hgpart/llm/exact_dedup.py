"""Exact deduplication by a 128-bit content hash, with bytes compared inside groups."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower, bounded_broadcast, join_groups, written


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "min", hash_bytes: int = 16) -> DataFrame:
    """One row per document: id, keep_id, group_size, kept, text_sha256.

    Texts are equal when identical after lower-casing A-Z (bytes otherwise
    unchanged). ``keep`` is ``min`` or ``max`` and says which id of a group
    stays. One pass hashes the texts; ids and hashes are grouped, 16 bytes a row; only rows whose hash occurs
    again have their bytes compared, by grouping on (hash, bytes), which Spark combines on
    the map side, so that thousands of copies leave each task as one row. Hashes that
    turn out to cover several texts are told apart by those bytes.

    Rows whose hash occurs once need no partner. Groups come to their rows (``join_groups``), so one of any size stays where its rows are.

    Null texts count as empty and equal each other. A null id is a row of its
    group like any other; it is kept only where the whole group has none. Rows
    that repeat an id and text are all returned and all kept if their id is.
    An empty table gives an empty result; other columns are ignored. ``hash_bytes`` < 16
    serves tests that force collisions.
    """
    best = {"min": F.min, "max": F.max}[keep]
    text = ascii_lower(F.coalesce(F.col(text_col).cast("string"), F.lit("")))
    source = docs.select(F.col(id_col).alias("id"), text.cast("binary").alias("body"))
    key = F.expr(f"substring(unhex(md5(body)), 1, {hash_bytes})").alias("h")
    rows = written(source.select("id", key, F.unhex(F.sha2("body", 256)).alias("sha")), "hashes")
    groups = written(rows.groupBy("h").agg(F.count("*").alias("n"), best("id").alias("keep_id")).filter("n > 1"), "again")
    again = groups.count()
    texts = source.select("id", key, "body").join(bounded_broadcast(groups.select("h"), again), "h", "left_semi")
    texts = texts.groupBy("h", "body").agg(F.count("*").alias("n"), best("id").alias("keep_id"))
    texts = written(texts, "texts")
    split = texts.groupBy("h").agg(F.count("*").alias("texts")).filter("texts > 1").select("h")
    n_split = split.count()
    out = join_groups(rows, groups, ["h"], "n", "left")
    if n_split:
        collided = source.select("id", key, "body").join(split, "h", "left_semi").withColumn("sha", F.unhex(F.sha2("body", 256)))
        out = out.join(split, "h", "left_anti").select("id", "keep_id", "n", "sha").union(collided.join(texts, ["h", "body"]).select("id", "keep_id", "n", "sha"))
    alone = F.col("n").isNull()
    keep_id = F.when(alone, F.col("id")).otherwise(F.col("keep_id"))
    return out.select(
        F.col("id").alias(id_col),
        keep_id.alias("keep_id"),
        F.coalesce("n", F.lit(1)).cast("long").alias("group_size"),
        F.col("id").eqNullSafe(keep_id).alias("kept"),
        F.lower(F.hex("sha")).alias("text_sha256"),
    )
