"""Query and oracle registry of the text operators: thin wrappers that derive the digest columns."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from kgfold.llm.common import shared_dir, table

Query = Callable[[SparkSession, str], DataFrame]


def op1_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    from kgfold.llm.html_paths import extract

    return extract(table(spark, sf_dir, "pages", "page_id", "url", "html"))


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from kgfold.llm.toxicity import score, train

    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    return score(docs, train(docs, table(spark, sf_dir, "labels", "doc_id", "toxic")))


def op3_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    from kgfold.llm.secret_scan import digest, scan

    return digest(scan(table(spark, sf_dir, "documents", "doc_id", "text")))


def op4_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from kgfold.llm.decontaminate import find_leaks

    return find_leaks(table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "benchmark", "item_id", "text"))


def op5_count_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from kgfold.llm.count_join import linked

    return linked(table(spark, sf_dir, "documents", "doc_id", "text"))


def op6_id_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from kgfold.llm.id_store import read_checks, write_store

    folder = f"{shared_dir(spark)}/id-store-{uuid.uuid4().hex}"
    write_store(table(spark, sf_dir, "documents", "doc_id", "text"), folder, public_tokenizers.path("word_bpe_49k.json"))
    return read_checks(spark, folder)


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from kgfold.llm.packing import pack

    return pack(table(spark, sf_dir, "documents", "doc_id", "text"), public_tokenizers.path("byte_bpe_50k.json"))


def op8_repeat_removal(spark: SparkSession, sf_dir: str) -> DataFrame:
    from kgfold.llm.repeat_cover import digest, remove_repeats

    return digest(remove_repeats(table(spark, sf_dir, "documents", "doc_id", "text")))


def op9_disclosure(spark: SparkSession, sf_dir: str) -> DataFrame:
    from kgfold.llm.disclosure import digest, sanitise

    return digest(sanitise(table(spark, sf_dir, "documents", "doc_id", "text")))


def op10_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    from kgfold.llm.weighted_sampling import fingerprints

    return fingerprints(table(spark, sf_dir, "documents", "doc_id", "text"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Query]:
    return {
        "op1_html_extraction": op1_html_extraction,
        "op2_toxicity": op2_toxicity,
        "op3_secret_scan": op3_secret_scan,
        "op4_decontamination": op4_decontamination,
        "op5_count_join": op5_count_join,
        "op6_id_store": op6_id_store,
        "op7_packing": op7_packing,
        "op8_repeat_removal": op8_repeat_removal,
        "op9_disclosure": op9_disclosure,
        "op10_fingerprints": op10_fingerprints,
        "pipeline": pipeline,
    }


def oracle_sql() -> dict[str, str]:
    return {}
