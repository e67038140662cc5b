"""From raw documents to token shards: toxicity, near duplicates, benchmark passages, mixing, token output."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hgpart.llm.common import bounded_broadcast, new_path, written
from hgpart.llm import decontaminate
from hgpart.llm.mixing import mix_sources
from hgpart.llm.ngram_join import ngram_components
from hgpart.llm.queries import table, tokenizer_path
from hgpart.llm.tokens import token_round_trip
from hgpart.llm.toxicity import fit_toxicity, score_toxicity, training_rows

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose score stays below 0.7."""
    model = fit_toxicity(training_rows(docs, table(spark, sf_dir, "labels")))
    return score_toxicity(docs, model, carry=COLUMNS).filter("predicted = 0").select(*COLUMNS)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents linked by shingle sets, the one with the smallest id; those without words all stay.

    Rows that repeat a kept id stay together: deciding between them is for exact deduplication.
    """
    found = ngram_components(docs)
    gone = written(found.filter("component_id < doc_id").select("doc_id").distinct(), "gone")
    return docs.join(bounded_broadcast(gone, gone.count()), "doc_id", "left_anti").select(*COLUMNS)


def drop_leaked(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without any benchmark window."""
    return decontaminate.drop_contaminated(docs, table(spark, sf_dir, "benchmark")).select(*COLUMNS)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it."""
    mixed = mix_sources(docs, carry=COLUMNS).filter("copies > 0")
    return mixed.withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int")))).select(*COLUMNS)


def write_token_shards(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token shards of every document, as read back from their files."""
    return token_round_trip(docs, tokenizer_path())


STAGES = [
    ("toxicity", drop_toxic),
    ("ngram_join", drop_near_copies),
    ("decontaminate", drop_leaked),
    ("mix_sources", mix),
    ("token_output", write_token_shards),
]

#: The fitted model, the rounding and the tokenizer have no SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        path = new_path(spark, f"stage-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
