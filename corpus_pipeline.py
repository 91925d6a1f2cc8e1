"""The corpus pipeline: toxic documents go, one document of each near-duplicate group stays, documents that hold test
items go, personal data is masked, and what is left is packed into training sequences.

Each stage takes (spark, docs, sf_dir) and works on all that its predecessor kept.  All but the last return the columns
of ``documents``; the last returns the pieces of packed sequences.  Rows without doc_id are kept by every filter that
does not concern their own text; an empty table passes through.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgfold.llm.common import staged, table

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def drop_toxic_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity model scores under 0.5; it learns from the labels of documents that are here."""
    from kgfold.llm.toxicity import drop_toxic, train

    docs = docs.select(*COLUMNS)
    return drop_toxic(docs, train(docs, table(spark, sf_dir, "labels", "doc_id", "toxic")))


def keep_one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str, broadcast_rows: int = 1_000_000) -> DataFrame:
    """The document with the least doc_id of each group of near duplicates (five-word shingles, similarity 0.8)."""
    from kgfold.llm.count_join import linked

    docs = docs.select(*COLUMNS)
    groups = linked(docs.select("doc_id", "text"))
    gone = staged(groups.filter("doc_id <> component_id").select("doc_id").distinct(), "gone")
    gone = F.broadcast(gone) if gone.count() <= broadcast_rows else gone
    kept = docs.join(gone, "doc_id", "left_anti").select(*COLUMNS)
    repeated = docs.groupBy("doc_id").count().filter("doc_id is not null and count > 1").limit(1).count()
    return kept.filter("doc_id is not null").dropDuplicates(["doc_id"]).union(kept.filter("doc_id is null")) if repeated else kept


def drop_contaminated_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item."""
    from kgfold.llm.decontaminate import drop_leaks

    return drop_leaks(docs.select(*COLUMNS), table(spark, sf_dir, "benchmark", "item_id", "text"))


def mask_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with identifiers and the terms that disclose them masked; n_chars follows the text."""
    from kgfold.llm.disclosure import sanitise

    clean = sanitise(docs.select(*COLUMNS))
    return clean.select("doc_id", F.col("clean_text").alias("text"), "lang", "source", F.char_length("clean_text").cast("long").alias("n_chars"))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents in sequences of 2048 tokens."""
    import public_tokenizers

    from kgfold.llm.packing import pack

    return pack(docs.select("doc_id", "text"), public_tokenizers.path("byte_bpe_50k.json"))


STAGES = [
    ("toxicity", drop_toxic_documents),
    ("near_duplicates", keep_one_of_each_group),
    ("decontamination", drop_contaminated_documents),
    ("personal_data", mask_personal_data),
    ("packing", pack_sequences),
]

#: No stage after the first can be told in SQL; tests/llm/test_streams.py compares each with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = staged(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
