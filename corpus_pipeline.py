"""A training corpus from raw documents: quality rules, line dedup, near-dedup, mixing and BPE coding, one operator a stage.

A stage takes (spark, docs, sf_dir) and gives a DataFrame; ``run`` writes each stage's rows as Parquet in the shared scratch folder and
rereads them as the next one's documents. All stages but the last give the columns of ``documents``, whatever further columns there are.

Null, empty and blank texts have no words and go in the first stage. Rows with a null id are judged by their text, take no part in comparisons with other rows, and
stay through ``lines`` and ``near_copies``. Rows that repeat an id and its text go or stay together; of an id with several texts, ``lines`` judges each for itself and
``near_copies`` keeps all or none. Ties go to the smaller id. An empty table passes through all stages. Texts of any length are read whole.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from topomap.llm import chunk_codec, line_dedup, mixing, near_dedup, quality_rules, shared


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base limits or the weighed rules reject go."""
    return quality_rules.keep_good(docs)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that resemble an earlier line go, and with them documents that had no other."""
    return line_dedup.drop_repeated_lines(docs)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of near copies the smallest doc_id stays."""
    return near_dedup.keep_one_each(docs)


def weights(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources reach their target weights: each document comes as often as its source's rate and its draw say."""
    return mixing.mix(docs, size=shared.word_count(F.col("text")))


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Ids of every document and whether decoding gives what the library's decode gives, as digests."""
    import public_tokenizers

    return chunk_codec.encode_documents(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [("quality", quality), ("lines", lines), ("near_copies", near_copies), ("weights", weights), ("tokens", tokens)]

#: SQL can't express the signatures, the set join's order of removal or the tokenizer; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, done = shared.load(spark, sf_dir, "documents"), None
    for name, stage in STAGES[:-1]:
        docs = shared.materialize(stage(spark, docs, sf_dir), f"stage-{name}")
        if done is not None:
            shared.discard(done)
        done = docs
    return STAGES[-1][1](spark, docs, sf_dir)
