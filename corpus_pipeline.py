"""The corpus pipeline: documents in, packed training sequences out. Part of the training-text operators."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from raydescent.llm.common import clear_cuts, cut, cuts, spare, table
from raydescent.llm.histogram_packing import pack_documents
from raydescent.llm.language_bayes import UNKNOWN, fit, learned_rows, predict
from raydescent.llm.patricia_dedup import exact_dedup
from raydescent.llm.queries import tokenizer
from raydescent.llm.simhash_dedup import near_dedup

#: A document is rejected below this posterior share of its best language.
LEAST_SHARE = 0.5


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Reject documents whose best language has a share below LEAST_SHARE; lang stays as it is.

    Shares are relative among the learned languages and nearly 1 for any longer text, so that in practice only texts
    without a letter are rejected; texts in a language that was not learned, or of random letters, stay.
    """
    model = fit(docs.where(learned_rows(F.col("doc_id"))))
    lang, share = spare(docs.columns, "lang_pred", "score")
    found = predict(docs, model, names=(lang, share))
    return found.where((F.col(lang) != UNKNOWN) & (F.col(share) >= LEAST_SHARE)).select(*[F.col(f"`{c}`") for c in docs.columns])


def drop_exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return exact_dedup(docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return near_dedup(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack_documents(docs, tokenizer("word_bpe_49k.json"))


STAGES = [("language_id", language_id), ("exact_dedup", drop_exact_copies), ("simhash_dedup", drop_near_copies), ("best_fit_packing", pack)]

#: No SQL: the classifier, the near-copy search and the packing are tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on documents, each on what the one before has written. What a stage has written for itself, and its
    input, are removed when its output stands."""
    docs = table(spark, sf_dir, "documents")
    before = set(cuts(spark))
    for name, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir), name)
        clear_cuts(spark, [path for path in cuts(spark)[:-1] if path not in before])
    return STAGES[-1][1](spark, docs, sf_dir)
