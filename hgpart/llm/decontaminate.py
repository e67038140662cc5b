"""Benchmark decontamination by a prefix-filtered join of word windows, in DataFrame functions alone."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import BROADCAST_ROWS, ascii_lower, bounded_broadcast, written

#: What separates words once A-Z are lower-cased.
NOT_WORD = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def words_of(text: str) -> Column:
    """Array of words; null and empty texts have none."""
    parts = F.split(F.trim(F.regexp_replace(ascii_lower(F.coalesce(F.col(text).cast("string"), F.lit(""))), NOT_WORD, " ")), " ")
    return F.array_remove(parts, "")


def item_windows(benchmark: DataFrame, id_col: str, text_col: str, length: int) -> DataFrame:
    """(win, items): each distinct run of ``length`` words of an item, or its whole text if shorter, with the sorted distinct item ids."""
    items = benchmark.select(F.col(id_col).cast("string").alias("item"), words_of(text_col).alias("w")).filter(F.size("w") > 0)
    starts = F.sequence(F.lit(0), F.greatest(F.size("w") - length, F.lit(0)))
    spread = items.select("item", F.explode(starts).alias("s"), "w").select("item", F.slice("w", F.col("s") + 1, F.lit(length)).alias("win"))
    return spread.groupBy("win").agg(F.array_sort(F.collect_set("item")).alias("items"))


#: Largest number of bytes of windows that one broadcast may hold; more windows take several scans.
BROADCAST_BYTES = 128 << 20


def _judged(docs: DataFrame, benchmark: DataFrame, id_col: str, text_col: str, item_col: str = "item_id", item_text: str = "text", length: int = 10, scan_rows: int = BROADCAST_ROWS, scan_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """One row per (id, hash of the text): the result columns, ``copies`` and ``version``."""
    windows = written(item_windows(benchmark, item_col, item_text, length), "windows")
    per_row = F.length(F.array_join("win", " ")) + F.length(F.array_join("items", ",")) + 64
    n_windows, n_bytes = windows.agg(F.count("*"), F.coalesce(F.sum(per_row), F.lit(0))).first()
    scans = max(1, -(-n_windows // scan_rows), -(-n_bytes // scan_bytes))
    vocabulary = written(windows.select(F.explode("win").alias("word")).distinct(), "vocabulary")
    n_vocabulary = vocabulary.count()
    source = docs.select(F.col(id_col).alias("c0"), F.xxhash64(text_col).alias("version"), words_of(text_col).alias("w"))
    occurring = source.select(F.explode("w").alias("word")).join(bounded_broadcast(vocabulary, n_vocabulary), "word")
    often = written(vocabulary.join(occurring.groupBy("word").agg(F.count("*").alias("n")), "word", "left").na.fill(0, ["n"]), "often")
    ranked = windows.select("win", "items", F.posexplode("win").alias("off", "word")).join(often, "word")
    filed = ranked.groupBy("win", "items").agg(F.min(F.struct("n", "word", "off")).alias("best")).select("win", "items", F.col("best.word").alias("word"), F.col("best.off").alias("off"))
    filed = written(filed.withColumn("scan", F.pmod(F.xxhash64("win"), F.lit(scans)).cast("int")), "filed")
    # the empty word stands at the head of every document and finds this row of the first scan
    head = docs.sparkSession.range(1).select(F.lit(None).cast("array<string>").alias("win"), F.lit(None).cast("array<string>").alias("items"), F.lit("").alias("word"), F.lit(0).alias("off"))
    found = None
    for scan in range(scans):
        block = filed.filter(F.col("scan") == scan).drop("scan")
        words = F.concat(F.array(F.lit("") if scan == 0 else F.lit(None).cast("string")), F.col("w"))
        spread = source.select("c0", "version", "w", F.posexplode(words).alias("pos", "word"))
        start = F.col("pos") - 1 - F.col("off")
        joined = spread.join(F.broadcast(block.union(head) if scan == 0 else block), "word").filter((F.col("word") == "") | ((start >= 0) & (start + F.size("win") <= F.size("w")) & (F.slice("w", F.greatest(start + 1, F.lit(1)), F.coalesce(F.greatest(F.size("win"), F.lit(0)), F.lit(0))) == F.col("win"))))
        part = joined.select("c0", "version", F.when(F.col("word") == "", F.size("w")).alias("n_words"), F.when(F.col("word") != "", F.struct(start.alias("start"), (start + F.size("win")).alias("end"))).alias("span"), "items")
        found = part if found is None else found.union(part)
    each = found.groupBy("c0", "version").agg(F.max("n_words").alias("n_words"), F.count("n_words").alias("copies"), F.array_sort(F.collect_set("span")).alias("spans"), F.array_sort(F.array_distinct(F.flatten(F.collect_set("items")))).alias("items"))
    merged = F.aggregate(
        "spans",
        F.struct(F.lit(0).alias("hit"), F.lit(0).alias("reach")),
        lambda acc, x: F.struct((acc["hit"] + F.greatest(F.lit(0), x["end"] - F.greatest(x["start"], acc["reach"]))).alias("hit"), F.greatest(acc["reach"], x["end"]).alias("reach")),
    )["hit"]
    out = each.select(
        F.col("c0").alias(id_col),
        F.col("n_words").cast("long").alias("n_words"),
        merged.cast("long").alias("n_hit"),
        F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join("items", ",").cast("binary"), 256).alias("items_sha256"),
        "copies",
        "version",
    ).withColumn("contaminated", F.col("n_hit") > 0)
    return out


def decontaminate(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text", length: int = 10, carry: tuple[str, ...] = (), scan_rows: int = BROADCAST_ROWS, scan_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """One row per document: id, n_words, n_hit, n_items, items_sha256, contaminated.

    Window and document stretch must agree in all words, so of the window's words
    in order of rarity a prefix of one is necessary: words are counted over all
    documents (only those that occur in a benchmark are counted), each
    window is filed under its rarest word with that word's offset, and document
    words join on it. The offset fixes where the window would lie; bounds on the
    position drop what would overhang the document, and the rest is compared word by word. Hits of a document
    are merged as intervals. Each document also sends one row without a hit, so no second join is needed.

    Windows are a stated query set, met in blocks: a block of at most ``scan_rows`` windows and about ``scan_bytes`` bytes, both
    counted, is broadcast and all documents pass by it, so that no document is ever moved to a frequent word. What is
    grouped by document carries (id, hash of the text) and hits, never a text.
    Null texts have no words and hit nothing; items without words are left out; null item ids
    mark words as hit but are not counted as items. Repeated rows are returned as often as they come in;
    rows that share an id but not a text are told apart by a hash of the text. Null ids are kept.
    Empty documents or an empty benchmark give zero rows or zero hits. ``carry`` names further columns to return, joined on id and
    hash at the end; those named like a result column give way to it.
    """
    out = _judged(docs, benchmark, id_col, text_col, item_col, item_text, length, scan_rows, scan_bytes)
    results = ["n_words", "n_hit", "n_items", "items_sha256", "contaminated"]
    extra = [c for c in dict.fromkeys(carry) if c not in (id_col, *results)]
    if not extra:
        return out.withColumn("copy", F.explode(F.array_repeat(F.lit(1), F.col("copies").cast("int")))).select(id_col, *results)
    own = docs.select(F.col(id_col).alias("c0"), F.xxhash64(text_col).alias("version"), *extra)
    found = out.withColumnRenamed(id_col, "_id").drop("copies").withColumnRenamed("version", "_version")
    return own.join(found, F.col("c0").eqNullSafe(F.col("_id")) & (F.col("version") == F.col("_version"))).select(F.col("c0").alias(id_col), *extra, *results)


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """``docs`` without the rows that contain a benchmark window; all columns stay.

    Only (id, hash of the text) of contaminated rows is joined back, broadcast if counted small.
    """
    found = _judged(docs, benchmark, id_col, text_col, **options).filter("contaminated").select(F.col(id_col).alias("_id"), F.col("version").alias("_version"))
    found = written(found, "contaminated")
    own = docs[id_col].eqNullSafe(F.col("_id")) & (F.xxhash64(docs[text_col]) == F.col("_version"))
    return docs.join(bounded_broadcast(found, found.count()), own, "left_anti")
