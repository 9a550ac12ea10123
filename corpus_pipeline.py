"""A corpus pipeline of the training-data operators, one Parquet table per stage.

What holds for all stages: an empty table gives an empty one; null texts are empty texts (the quality rules reject
them), null sources have no host verdict, and rows without an id are judged like others and are near copies of nothing;
repeated rows are judged each, but of rows equal in id and words one stays, the one whose text is least; a very long text
is one row of one task and is read whole; further columns pass through all stages but the last, under any names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from motifmill.functions.scratch import materialise
from motifmill.llm.bpe import encode_documents
from motifmill.llm.decontaminate import drop_leaking
from motifmill.llm.jaccard import keep_one_of_each
from motifmill.llm.pii import redact_documents
from motifmill.llm.quality import keep_good


def tokenizer_path() -> str:
    """Path of the tokenizer file of the last stage."""
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the quality rules of their own text and of their host."""
    return keep_good(docs)


def near_copies_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies: five-word shingles similar by 0.8 and more."""
    return keep_one_of_each(docs)


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that leak no item of ``benchmark``."""
    return drop_leaking(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def privacy_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with personal data replaced by the names of its kinds; ``n_chars`` follows the text."""
    clean = redact_documents(docs)
    return clean.withColumn("n_chars", F.length("text").cast("bigint")) if "n_chars" in docs.columns else clean


def encoding_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents as token ids, beside the text that was encoded."""
    encoded = encode_documents(docs, tokenizer_path(), carry=("source", "text"))
    return encoded.select(F.col("key").alias("doc_id"), "source", "text", F.size("ids").cast("bigint").alias("n_tokens"), "ids")


STAGES = [
    ("quality rules", quality_stage),
    ("simhash near-dedup", near_copies_stage),
    ("benchmark decontamination", decontamination_stage),
    ("personal data", privacy_stage),
    ("bpe encoding", encoding_stage),
]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written and read again before the next."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
