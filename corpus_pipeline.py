"""A training-data pipeline over ``documents``: five stages, each written as Parquet and read again as the next one's input.

quality: documents that the classifier rejects go. near_dedup: one document of each group of near
copies (five words, similarity 0.8) stays. decontamination: documents that hold a benchmark passage
go. secrets: found spans are masked in the text. packing: the remaining documents become sequences
of token ids with a loss mask.
All but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from coltypes.llm import common, decontam, neardup, packing, quality, queries, secrets


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the compression classifier, fitted on all labels, scores below its threshold go."""
    return quality.keep_good(docs, quality.fit(docs, common.table(spark, sf_dir, "labels")))


def near_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies (five words, similarity 0.8) stays."""
    return neardup.keep_one(docs)


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold half of a benchmark item's words under tiles go."""
    return decontam.keep_clean(docs, common.table(spark, sf_dir, "benchmark"))


def secrets_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sure and linked secrets are masked in the text; n_chars follows."""
    return secrets.mask(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of packed sequences with token ids and loss mask; a smaller store of pieces leaves room beside what earlier stages hold."""
    return packing.pack_sequences(docs, queries.tokenizer(queries.WORDS), 1, packing.Settings(store=150_000))


STAGES = [
    ("quality", quality_stage),
    ("near_dedup", near_dedup_stage),
    ("decontamination", decontamination_stage),
    ("secrets", secrets_stage),
    ("packing", packing_stage),
]

#: Compression, hashing, tiling and tokenizers are outside SQL; tests/llm checks the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages; the table of each is deleted once the next one is written, the last one's is what the result reads."""
    docs = common.table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs, path = common.stored(stage(spark, docs, sf_dir), f"pipeline-{name}")
        if name != STAGES[0][0]:
            common.remove(spark, last)
        last = path
    return docs
