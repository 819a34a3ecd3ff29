"""From raw documents to packed training sequences.

Five stages, each on all that the stage before kept: language ID, SimHash near-duplicates, repeated
strings, benchmark leaks, best-fit packing. ``run`` writes each stage's rows as Parquet to shared
storage and reads them again as the next stage's documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockpress.llm.common import stored, table
from blockpress.llm.queries import vocabulary


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in a known language, by text and source; the text model is fitted on a bounded sample of their labels."""
    from blockpress.llm.language_id import TextModel, document_evidence, identify

    text_hash = F.xxhash64(F.coalesce("text", F.lit("")))
    rows = document_evidence(docs).withColumn("text_hash", text_hash)
    found = identify(rows, TextModel.fit_on(docs), ["doc_id", "text_hash"])
    gone = found.where("not kept").select(F.col("doc_id").alias("_d"), F.col("text_hash").alias("_t")).distinct()
    whole = docs.select("doc_id", text_hash.alias("_h"), F.struct(*docs.columns).alias("_row"))
    return whole.join(gone, whole["doc_id"].eqNullSafe(gone["_d"]) & (whole["_h"] == gone["_t"]), "left_anti").select("_row.*")


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate group stays (five words, 0.8): the one with the least id."""
    from blockpress.llm.simhash import one_of_each

    return one_of_each(docs)


def repeat_removal(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the strings of 200 bytes that occur elsewhere too."""
    from blockpress.llm.suffix_dedup import without_repeats

    return without_repeats(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no passage of the benchmark."""
    from blockpress.llm.decontaminate import drop_contaminated

    return drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sequences of at most 2048 tokens: each piece of each document and its place."""
    from blockpress.llm.packing import best_fit_pack

    return best_fit_pack(docs, vocabulary("word_bpe_49k.json"), 2048)


STAGES = [
    ("language ID", language_id),
    ("SimHash near-dedup", near_dedup),
    ("suffix-array dedup", repeat_removal),
    ("benchmark decontamination", decontamination),
    ("best-fit packing", packing),
]

#: Tokens, fingerprints and the language model are beyond SQL; tests hold each stage against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = stored(docs, f"stage-{k}")
    return docs
