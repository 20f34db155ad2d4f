"""The corpus pipeline: toxic documents go, near copies go, sources are mixed, texts become token ids."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from crowding.llm.bpe_automaton import encode_column
from crowding.llm.common import settle, table
from crowding.llm.jaccard_join import keep_one
from crowding.llm.poisson_mix import mix
from crowding.llm.toxicity import score, train

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
#: Rows and bytes that Spark hands to a Python worker at a time, and bytes of ids a worker keeps: executors of 3 GB run all stages.
BATCH = {"spark.sql.execution.arrow.maxRecordsPerBatch": "2000", "spark.sql.execution.arrow.maxBytesPerBatch": "8388608"}
CACHE = 24 << 20
#: No SQL expresses a fitted model or a BPE automaton.
ORACLE_SQL = None


def small_batches(spark: SparkSession) -> None:
    """Both are settings of a running session; they hold until set anew, as stages are computed after they return."""
    for key, value in BATCH.items():
        if spark.conf.isModifiable(key):
            spark.conf.set(key, value)


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose expected grade is not toxic; the model is fitted on labelled documents of the input."""
    small_batches(spark)
    return score(docs, train(docs, table(spark, sf_dir, "labels"))).filter("toxic = 0").select(*docs.columns)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group that shares 5-word shingles at Jaccard 0.8."""
    small_batches(spark)
    return keep_one(docs, 5, 80, 100)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Poisson repetitions to shares that go with the square root of a source's size, shuffled."""
    return mix(docs).select(*docs.columns)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, source, n_tokens and ids of every row."""
    import public_tokenizers

    small_batches(spark)
    out = encode_column(docs.select("doc_id", "source", "text"), str(public_tokenizers.path("byte_bpe_50k.json")), cache=CACHE)
    return out.select("doc_id", "source", F.size("ids").cast("long").alias("n_tokens"), "ids")


STAGES = [("toxicity", drop_toxic), ("near_copies", drop_near_copies), ("mixing", mix_sources), ("bpe", encode)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each is written and read again before the next."""
    docs = table(spark, sf_dir, "documents").select(*COLUMNS)
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = settle(docs, f"pipeline-{name}")
    return docs
