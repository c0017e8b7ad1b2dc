"""A training-corpus pipeline over ``documents``: language identification, near-duplicate removal, substring removal, benchmark
decontamination and packing.  Each stage takes all rows that the stage before it kept; its result is written and read again.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from thriftline.llm import decontaminate, language_id, near_dedup, packing, rowkeys, substring_dedup
from thriftline.llm.arrowrun import fresh
from thriftline.llm.queries import tokenizer_path
from thriftline.shipping import written

#: No language is taken for known below this likeness to its own text, less 1 / sqrt(n) for what n different n-grams may miss by chance.
LEAST_SCORE = 0.3
#: Near duplicates share this percentage of their five-word shingles.
SHINGLE, PERCENT = 5, 80


def keep_known_languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in a language learned from the corpus; those without letters or less alike than ``LEAST_SCORE`` go.

    The likeness is that to the best language alone, so it does not depend on how many others were learned.
    """
    out, (lang, alike, grams) = language_id.likened(docs, language_id.learned(docs))
    enough = F.col(alike) >= LEAST_SCORE - 1 / F.sqrt(grams)
    return out.where((F.col(lang) != "und") & enough).select(*docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate group: that of the smallest doc_id.  Rows without doc_id stay.

    Only rows that repeat doc_id and text together are one document; see ``rowkeys.told_apart``.
    """
    key = fresh("row_key", docs.columns)
    told = rowkeys.told_apart(docs, key)
    found = near_dedup.grouped(told, key, SHINGLE, PERCENT)
    gone = found.where("key <> component").select(F.col("key").alias(key)).distinct()
    known = told.docs.where(F.col(key).isNotNull()).join(gone, key, "left_anti")
    if told.repeated:
        known = known.dropDuplicates([key])
    return known.select(*docs.columns).unionByName(docs.where("doc_id is null"))


def drop_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the words of windows that start earlier; a text that loses nothing stays as it is."""
    out, (text, _, removed) = substring_dedup.cleaned(docs)
    changed = F.col(removed) > 0
    new_text = F.when(changed, F.col(text)).otherwise(F.col("text"))
    out = out.withColumn(text, new_text).withColumn("n_chars", F.when(changed, F.length(text).cast("long")).otherwise(F.col("n_chars")))
    return out.drop("text").withColumnRenamed(text, "text").select(*docs.columns)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which no benchmark window occurs."""
    out, (_, items, _) = decontaminate.marked(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    return out.where(F.size(items) == 0).select(*docs.columns)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents in sequences of at most 4096 tokens."""
    return packing.pack_documents(docs, tokenizer_path("word_bpe_49k.json"))


STAGES = [
    ("language_id", keep_known_languages),
    ("near_dedup", drop_near_duplicates),
    ("substring_dedup", drop_repeated_passages),
    ("decontaminate", drop_contaminated),
    ("packing", pack),
]

#: Learned profiles and a tokenizer are beyond SQL; tests/llm holds a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written to the shared folder and read again."""
    out = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for n, (_, stage) in enumerate(STAGES):
        out = stage(spark, out, sf_dir)
        if n < len(STAGES) - 1:
            out = written(out)
    return out
