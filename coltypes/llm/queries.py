"""The eleven queries of this subpackage: ten operators on their whole tables, and the pipeline.

None has an oracle in SQL (hashing, compression, tokenizers and alignment are outside it); tests/llm
holds each against brute force, an exact round trip or held-out labels.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from pyspark.sql import functions as F

from coltypes.llm import common, decontam, langid, licenses, neardup, packing, pii, quality, records, secrets, simhash

#: Where the tokenizer files lie; a parameter of the operators, taken from the installed package.
BYTES, WORDS = "byte_bpe_50k.json", "word_bpe_49k.json"


def tokenizer(name: str) -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return common.table(spark, sf_dir, "documents")


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per license notice found: doc_id, name, coverage, span in code points."""
    return licenses.scan(documents(spark, sf_dir))


def op2_compression_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per document: doc_id, held_out, score, predicted. Labels of ids with crc32 mod 5 = 0 (and of null ids) are held out."""
    docs = documents(spark, sf_dir)
    model = quality.fit(docs, common.table(spark, sf_dir, "labels"), lambda i: common.id_remainder(i, 5) != 0)
    held_out = F.coalesce(common.id_remainder(F.col("doc_id"), 5) == 0, F.lit(True))
    return quality.score(docs, model).select("doc_id", held_out.alias("held_out"), "score", "predicted")


def op3_feistel_pseudonyms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per document: doc_id, the text with pseudonyms, how many values were found and how many changed."""
    return pii.pseudonymise(documents(spark, sf_dir))


def op4_binary_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per document, read back from the files: doc_id, start, n_tokens, ids_crc32. The files are what the operator makes; they stay."""
    return records.read_back(records.write(documents(spark, sf_dir), tokenizer(BYTES), 2, common.fresh_path(spark, "records")))


def op5_greedy_tiling_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per document and benchmark item that it holds: doc_id, item_id, coverage, n_tiles, covered_words."""
    return decontam.find(documents(spark, sf_dir), common.table(spark, sf_dir, "benchmark"))


def op6_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id, kept."""
    return neardup.groups(documents(spark, sf_dir), neardup.Settings(width=4, percent=80))


def op7_kneser_ney_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per document: doc_id, held_out, lang_pred, score, rejected. Documents of ids with crc32 mod 4 = 2 (and of null ids) are held out."""
    docs = documents(spark, sf_dir)
    model = langid.fit(docs, lambda i: common.id_remainder(i, 4) != 2)
    held_out = F.coalesce(common.id_remainder(F.col("doc_id"), 4) == 2, F.lit(True))
    return langid.predict(docs, model).select("doc_id", held_out.alias("held_out"), "lang_pred", "score", "rejected")


def op8_vector_bin_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per piece of the sequences of ``packing.pack_sequences``, told by the checksum of its ids."""
    return packing.digest(packing.pack_sequences(documents(spark, sf_dir), tokenizer(WORDS), 1))


def op9_multipart_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per document: doc_id, n_assign, n_access, n_hex, n_linked, base_sha256, spans."""
    return secrets.find(documents(spark, sf_dir))


def op10_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract columns, and the class of each document among fingerprints within the radius."""
    compared, _ = common.stored(simhash.compare_edited(documents(spark, sf_dir)), "simhash-rows")
    prints = compared.select("doc_id", F.conv("fingerprint", 16, -10).cast("long").alias("fingerprint"))
    classes = simhash.near_classes(prints).where("doc_id is not null").groupBy("doc_id").agg(F.min("class_id").alias("class_id"))
    return compared.join(classes, "doc_id", "left")


def packed_conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whole conversations as items under limits on tokens, segments and loss-bearing (assistant) tokens, which bind each by itself."""
    items = packing.conversation_items(common.table(spark, sf_dir, "conversations"), tokenizer(WORDS), 1)
    return packing.assign(items, packing.Settings(loss=1024, segments=16, cut=False)).withColumnRenamed("item_id", "conv_id")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    ops = (op1_license_scan, op2_compression_quality, op3_feistel_pseudonyms, op4_binary_records, op5_greedy_tiling_decontamination, op6_minhash_near_dedup, op7_kneser_ney_language, op8_vector_bin_packing, op9_multipart_secrets, op10_simhash, packed_conversations)
    return {f.__name__: f for f in ops}


def oracle_sql() -> dict[str, str]:
    return {}
