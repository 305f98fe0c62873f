"""The registered queries of the training-text operators, thin over the operators, and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from raydescent.llm.common import new_folder, table
from raydescent.llm.oracles import ORACLES  # noqa: F401


def op2_nn_descent(spark: SparkSession, sf_dir: str) -> DataFrame:
    from raydescent.llm.nn_descent import vector_components

    return vector_components(table(spark, sf_dir, "embeddings").select("vec_id", "embedding"))


def op3_separator_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """documents written as flat files of the byte-level vocabulary with its end-of-text id, then counted by the scan."""
    from raydescent.llm.separator_scan import count_tokens, flat_files, write_flat

    folder = new_folder(spark, "flat")
    written = write_flat(table(spark, sf_dir, "documents").select("doc_id", "text"), tokenizer("byte_bpe_50k.json"), 50_256, folder, compress=True)
    counted = count_tokens(flat_files(spark, f"{folder}/*.bin.zst"), 50_256)
    named = counted.withColumn("stream", F.substring_index("stream", "/", -1)).join(written, ["stream", "number"])
    return named.select(F.col("id").alias("doc_id"), "n_tokens")


def op4_bpe_automaton(spark: SparkSession, sf_dir: str) -> DataFrame:
    from raydescent.llm.bpe_automaton import encode_digests

    return encode_digests(table(spark, sf_dir, "documents").select("doc_id", "text"), tokenizer("byte_bpe_50k.json"))


def op5_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from raydescent.llm.patricia_dedup import assign_owners

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return assign_owners(docs).select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


def tokenizer(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_host_reputation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Outcomes: the labels of the document with a page's number; good is quality without toxicity."""
    from raydescent.llm.url_reputation import judge_urls

    labels = table(spark, sf_dir, "labels")
    good = labels.select(F.col("doc_id").alias("page_id"), ((F.col("quality") == 1) & (F.col("toxic") == 0)).cast("int").alias("good"))
    judged = judge_urls(table(spark, sf_dir, "pages").select("page_id", "url"), good)
    return judged.withColumn("good_upper", F.round("good_upper", 6))


def op6_license_votes(spark: SparkSession, sf_dir: str) -> DataFrame:
    from raydescent.llm.license_votes import scan_licenses

    return scan_licenses(table(spark, sf_dir, "documents").select("doc_id", "text")).withColumn("score", F.round("score", 6))


def op7_simhash_planes(spark: SparkSession, sf_dir: str) -> DataFrame:
    from raydescent.llm.simhash_dedup import simhash_components

    return simhash_components(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op8_histogram_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from raydescent.llm.histogram_packing import pack_documents

    return pack_documents(table(spark, sf_dir, "documents").select("doc_id", "text"), tokenizer("word_bpe_49k.json"))


def op9_stupid_backoff(spark: SparkSession, sf_dir: str) -> DataFrame:
    from raydescent.llm.backoff_lm import backoff_scores

    return backoff_scores(table(spark, sf_dir, "documents").select("doc_id", "text"), tokenizer("byte_bpe_50k.json"))


def op10_language_bayes(spark: SparkSession, sf_dir: str) -> DataFrame:
    from raydescent.llm.language_bayes import fit, learned_rows, predict

    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    model = fit(docs.where(learned_rows(F.col("doc_id"))))
    found = predict(docs.select("doc_id", "text"), model)
    return found.select("doc_id", (~learned_rows(F.col("doc_id"))).alias("held_out"), "lang_pred", "score")


QUERIES = {f.__name__: f for f in (op1_host_reputation, op2_nn_descent, op3_separator_scan, op4_bpe_automaton, op5_exact_dedup, op6_license_votes, op7_simhash_planes, op8_histogram_packing, op9_stupid_backoff, op10_language_bayes)}
