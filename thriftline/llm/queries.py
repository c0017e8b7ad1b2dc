"""The registered queries of the training-data operators and, where SQL can express one, its DuckDB statement."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from thriftline.llm import decontaminate, html_extract, language_id, near_dedup, oracles, packing, quality_classifier, quality_rules, sharding, substring_dedup, tokens


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokenizer_path(name: str) -> str:
    """A public tokenizer file; only these queries name one, the operators take a path."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_duplicates(_table(spark, sf_dir, "documents"))


def op2_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = substring_dedup.substring_dedup(_table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", "n_removed", F.sha2("text", 256).alias("kept_sha256"))


def op3_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_documents(_table(spark, sf_dir, "documents"))


def op4_html_extract(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_extract.extract(_table(spark, sf_dir, "pages"))


def op5_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = packing.pack_documents(_table(spark, sf_dir, "documents"), tokenizer_path("word_bpe_49k.json"))
    return out.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")


def pack_conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whole conversations under all three limits, tokens being words: each with its sizes, and whether its sequence keeps the limits."""
    words = F.size(F.filter(F.split(F.coalesce("text", F.lit("")), "[ \\t-\\r]+"), lambda w: w != "")).cast("long")
    said = F.when(F.col("role") == "assistant", words).otherwise(F.lit(0))
    examples = _table(spark, sf_dir, "conversations").groupBy("conv_id").agg(F.sum(words).alias("n_tokens"), F.sum(said).cast("long").alias("n_loss"))
    packed = packing.pack_examples(examples.withColumnRenamed("conv_id", "example_id"))
    rows = packed.join(examples, F.col("example_id") == F.col("conv_id"))
    sums = rows.groupBy("sequence_id").agg(((F.sum("n_tokens") <= 4096) & (F.count("*") <= 64) & (F.sum("n_loss") <= 2048) | (~F.min("fits") & (F.count("*") == 1))).alias("kept_limits"))
    return rows.join(sums, "sequence_id").select("conv_id", "n_tokens", "n_loss", "fits", "kept_limits")


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokens.token_counts(_table(spark, sf_dir, "documents"), tokenizer_path("byte_bpe_50k.json"))


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.apply_rules(_table(spark, sf_dir, "documents")).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op8_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_classifier.grade_documents(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


def op9_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id.identify_languages(_table(spark, sf_dir, "documents"))


def op10_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = decontaminate.decontaminate(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))
    return out.select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")


QUERIES = {
    "op1_near_dedup": op1_near_dedup,
    "op2_substring_dedup": op2_substring_dedup,
    "op3_sharding": op3_sharding,
    "op4_html_extract": op4_html_extract,
    "op5_packing": op5_packing,
    "pack_conversations": pack_conversations,
    "op6_token_counts": op6_token_counts,
    "op7_quality_rules": op7_quality_rules,
    "op8_quality_classifier": op8_quality_classifier,
    "op9_language_id": op9_language_id,
    "op10_decontaminate": op10_decontaminate,
}

ORACLES = {
    "op1_near_dedup": oracles.NEAR_DEDUP,
    "op2_substring_dedup": oracles.SUBSTRING,
    "op7_quality_rules": oracles.QUALITY_RULES,
    "op10_decontaminate": oracles.DECONTAMINATE,
    "pack_conversations": oracles.PACK_CONVERSATIONS,
}
