"""Queries of the ten training-data operators and of the pipeline: thin layers that bring operators to their contracts' columns."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import automaton_dedup, chunk_codec, embedding_dedup, kd_shards, line_dedup, mixing, near_dedup, quality_rules, shared, suffix_dedup, token_counts, twins


def _vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    report = quality_rules.quality_report(shared.load(spark, sf_dir, "documents"))
    return report.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op2_bpe_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chunk_codec.encode_documents(shared.load(spark, sf_dir, "documents"), _vocabulary("word_bpe_49k.json"))


def op3_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embedding_dedup.linked_vectors(shared.load(spark, sf_dir, "embeddings"))


def op4_minhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, component_id (smallest doc_id of its class of near copies), kept."""
    documents = shared.load(spark, sf_dir, "documents")
    classes = near_dedup.near_duplicates(documents).select(F.col("id").alias("doc_id"), "component").dropDuplicates(["doc_id"])
    component = F.coalesce("component", "doc_id")
    return documents.select("doc_id").join(classes, "doc_id", "left").select("doc_id", component.alias("component_id"), F.coalesce(component == F.col("doc_id"), F.lit(True)).alias("kept"))


def op5_kd_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    placed = kd_shards.shard_documents(shared.load(spark, sf_dir, "documents"), shards=16)
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op6_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.remove_repeated_bytes(shared.load(spark, sf_dir, "documents"))


def op7_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    plan = mixing.mixing_plan(shared.load(spark, sf_dir, "documents"), size=shared.word_count(F.col("text")))
    return plan.select("doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).alias("taken"))


def op8_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.line_report(shared.load(spark, sf_dir, "documents"))


def op9_automaton_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return automaton_dedup.remove_repeated_words(shared.load(spark, sf_dir, "documents"))


def op10_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.count_tokens(shared.load(spark, sf_dir, "documents"), _vocabulary("byte_bpe_50k.json"), limit=512)


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    own = [op1_quality_rules, op2_bpe_codec, op3_embedding_dedup, op4_minhash_dedup, op5_kd_shards, op6_suffix_dedup, op7_mixing, op8_line_dedup, op9_automaton_dedup, op10_token_counts]
    return {f.__name__: f for f in own} | {"pipeline": pipeline}


def oracle_sql() -> dict[str, str]:
    """Twins of the queries that SQL can express. Those of 3, 4, 6, 8 and 9 compare rows in plain joins and are for small tables; tokenizers (2, 10), the k-d tree (5) and the pipeline have none."""
    return {
        "op1_quality_rules": twins.OP1, "op3_embedding_dedup": twins.OP3, "op4_minhash_dedup": twins.OP4, "op6_suffix_dedup": twins.OP6, "op7_mixing": OP7_SQL,
        "op8_line_dedup": twins.OP8, "op9_automaton_dedup": twins.OP9,
    }


#: Seeds as in mixing.mixing_rates; sums and quotients in the same order.
OP7_SQL = r"""
WITH sized AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size FROM documents),
sources AS (SELECT source, sum(size)::BIGINT AS source_size FROM sized GROUP BY source),
weighed AS (SELECT *, ((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1)::DOUBLE AS weight, sum(source_size) OVER () AS total FROM sources),
levels AS (SELECT *, (total - 3 * coalesce(sum(source_size) OVER w, 0))::DOUBLE / (sum(weight) OVER () - coalesce(sum(weight) OVER w, 0)) AS level
  FROM weighed WINDOW w AS (ORDER BY source_size / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
filled AS (SELECT *, level * weight >= 3 * source_size AS is_full FROM levels),
targets AS (SELECT source, source_size, CASE WHEN is_full THEN (3 * source_size)::DOUBLE ELSE max(CASE WHEN NOT is_full THEN level END) OVER () * weight END AS target FROM filled),
rates AS (SELECT *, CASE WHEN source_size > 0 THEN target / source_size ELSE 0 END AS rate FROM targets),
drawn AS (SELECT r.source, s.range AS seed, sum(CASE WHEN ('0x' || substr(md5(s.range || ':' || coalesce(d.doc_id::VARCHAR, 'null')), 1, 8))::UBIGINT / 4294967296.0::DOUBLE < rate - floor(rate) THEN size ELSE 0 END) AS extra
  FROM sized d JOIN rates r ON d.source IS NOT DISTINCT FROM r.source, range(32) s GROUP BY ALL),
chosen AS (SELECT d.source, min(struct_pack(miss := abs(extra + floor(rate) * source_size - target), seed := seed)).seed AS seed
  FROM drawn d JOIN rates r ON d.source IS NOT DISTINCT FROM r.source GROUP BY d.source)
SELECT doc_id, size, source_size, target,
  ((floor(rate) + CASE WHEN ('0x' || substr(md5(c.seed || ':' || coalesce(doc_id::VARCHAR, 'null')), 1, 8))::UBIGINT / 4294967296.0::DOUBLE < rate - floor(rate) THEN 1 ELSE 0 END) * size)::BIGINT AS taken
FROM sized d JOIN rates r ON d.source IS NOT DISTINCT FROM r.source JOIN chosen c ON d.source IS NOT DISTINCT FROM c.source
"""
