"""The registered queries of this subpackage: thin digests over its operators."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from packflow.llm.common import read_table


def op1_tiff(spark: SparkSession, sf_dir: str) -> DataFrame:
    from packflow.llm.tiff import media_digest, texts_to_tiff

    return media_digest(texts_to_tiff(read_table(spark, sf_dir, "documents")))


def op2_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    from packflow.llm.warc import page_records

    return page_records(read_table(spark, sf_dir, "pages"))


def op3_bm25(spark: SparkSession, sf_dir: str) -> DataFrame:
    from packflow.llm.bm25 import leaked_items

    return leaked_items(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark"))


def op4_suffix(spark: SparkSession, sf_dir: str) -> DataFrame:
    from packflow.llm.suffix import remove_repeats

    return remove_repeats(read_table(spark, sf_dir, "documents"))


def op5_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from packflow.llm.quality import quality_scores

    return quality_scores(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from packflow.llm.toxicity import toxicity_scores

    return toxicity_scores(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))


def op6_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from packflow.llm.records import record_digest

    return record_digest(read_table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def op7_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    from packflow.llm.pii import pii_digest

    return pii_digest(read_table(spark, sf_dir, "documents"))


def op8_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from packflow.llm.simhash import near_duplicates

    return near_duplicates(read_table(spark, sf_dir, "documents")).selectExpr("doc_id", "lower(lpad(hex(fingerprint), 16, '0')) as fingerprint", "component_id")


def op10_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from packflow.llm.sentencepiece_bpe import piece_digest

    return piece_digest(read_table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = {k: f for k, f in globals().items() if k.startswith("op") and callable(f)}
    return dict(sorted(found.items(), key=lambda x: int(x[0][2:].split("_")[0])))


def oracle_sql() -> dict[str, str]:
    from packflow.llm.oracles import ORACLES

    return dict(ORACLES)
