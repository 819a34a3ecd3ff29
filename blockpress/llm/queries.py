"""The queries of the corpus operators: each applies one operator to its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockpress.llm.common import table


def vocabulary(name: str) -> str:
    """Path of a public tokenizer file."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op5_token_binary(spark: SparkSession, sf_dir: str) -> DataFrame:
    from blockpress.llm.token_binary import encode_to_file_and_back

    return encode_to_file_and_back(table(spark, sf_dir, "documents"), vocabulary("byte_bpe_50k.json"))


def op8_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from blockpress.llm.packing import best_fit_pack

    return best_fit_pack(table(spark, sf_dir, "documents"), vocabulary("word_bpe_49k.json"), 2048)


def op1_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from blockpress.llm.suffix_dedup import removal_digests

    return removal_digests(table(spark, sf_dir, "documents"))


def op2_minhash_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    from blockpress.llm.minhash import edited_fingerprints

    return edited_fingerprints(table(spark, sf_dir, "documents"))


def minhash_similar_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The other half of operator 2: bands joined, pairs verified by exact Jaccard similarity."""
    from blockpress.llm.minhash import similar_documents

    return similar_documents(table(spark, sf_dir, "documents"))


def op3_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from blockpress.llm.token_count import count_tokens

    return count_tokens(table(spark, sf_dir, "documents"), vocabulary("piece_bpe_32k.model"))


def op4_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from blockpress.llm.simhash import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents"))


#: Rules on urls, and hosts that a small list names.
URL_RULES = (("com", "/", "allow"), ("example.com", "/en/", "block"), ("www.example.com", "/en/", "allow"), ("net", "/es/", "block"), ("net", "/fr/", "block"))
LISTED_HOSTS = ("spam-farm.example.org", "cheap-pills.example.com", "adult-x.example.net")


def op6_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every page; where no rule fits, hosts with a hyphen in their name and addresses that some link tracks are blocked."""
    from blockpress.llm.url_filter import Rule, filter_urls, with_parts

    pages = table(spark, sf_dir, "pages")
    hosts = with_parts(pages).where("contains(host, '-')").select(F.col("host").alias("key")).distinct()
    tracked = with_parts(pages.where(r"url rlike '[?&](ref|utm_source)='")).select(F.concat("host", "path").alias("key")).distinct()
    return filter_urls(pages, [Rule(*r) for r in URL_RULES], hosts, tracked)


def op7_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every page: its text, declared language, address and host; the text model is fitted on labelled documents."""
    from blockpress.llm.language_id import TextModel, identify, page_evidence

    model = TextModel.fit_on(table(spark, sf_dir, "documents"))
    return identify(page_evidence(table(spark, sf_dir, "pages")), model, "page_id")


def op9_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from blockpress.llm.decontaminate import contaminated

    return contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op10_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    from blockpress.llm.chat import conversation_digests, format_conversations

    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    probe = spark.range(2).selectExpr("-1L as conv_id", "id as turn", "if(id = 0, 'user', 'assistant') as role", "'</s>[INST] ok [/INST]' as text")
    return conversation_digests(format_conversations(turns.unionByName(probe)))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    made = (op1_suffix_dedup, op2_minhash_fingerprints, op3_token_counts, op4_simhash_near_dedup, op5_token_binary, op6_url_filter, op7_language_id, op8_best_fit_packing, op9_decontamination, op10_chat_format, minhash_similar_documents)
    return {f.__name__: f for f in made}


def oracle_sql() -> dict[str, str]:
    from blockpress.llm.sql import OP1, OP6, OP10, SIMILAR

    return {"op1_suffix_dedup": OP1, "op6_url_filter": OP6, "op10_chat_format": OP10, "minhash_similar_documents": SIMILAR}
