"""A training corpus from ``documents``: language ID, near-dedup, decontamination, PII, byte-level BPE.

Each stage takes (spark, docs, sf_dir) and works on all rows that the one before kept; all but the last
return the columns of ``documents``.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from overlapkeys.llm.bpe_replay import encode_documents
from overlapkeys.llm.common import arrow_rows, documents, settle
from overlapkeys.llm.langid import language_of, train
from overlapkeys.llm.latent_decontam import leaks
from overlapkeys.llm.pii_crf import personal_data, trained_field
from overlapkeys.llm.simhash_golay import near_copies

LEAST_SCORE = 0.5  # of the language that a document is given
KEPT_WORDS = 100_000  # of language ID, twice as many of BPE: workers hold what other stages keep, too
TEXTS, NUMBERS = 500, 4_000  # rows of an Arrow batch where whole texts pass, and where numbers do


def _fresh(docs: DataFrame, name: str) -> str:
    """``name``, made longer while a column of ``docs`` has it."""
    taken = {c.lower() for c in docs.columns}
    while name.lower() in taken:
        name += "_"
    return name


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents without letters and those whose language stays in doubt.

    A null or empty text has no letters; repeated rows fare alike; an empty table stays empty.
    """
    arrow_rows(spark, TEXTS)
    model, told = train(docs, public_tokenizers.path("piece_bpe_32k.model")), _fresh(docs, "told")
    found = docs.select("*", language_of(model, KEPT_WORDS)("text").alias(told))
    sure = (F.col(told)["lang_pred"] != "und") & (F.col(told)["score"] >= LEAST_SCORE)
    return found.filter(sure).select(*docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document with the least doc_id of each group of near copies; of repeated rows one.

    A null doc_id counts as the greatest. Texts of fewer words than a shingle group with equal ones; an
    empty table stays empty.
    """
    arrow_rows(spark, NUMBERS)
    u, rank = _fresh(docs, "u"), _fresh(docs, "rank")
    kept = near_copies(docs).filter("keep").select(F.col("u").alias(u)).distinct()
    own = docs.withColumn(u, F.xxhash64(F.col("doc_id").cast("long"), F.coalesce("text", F.lit(""))))
    once = own.join(kept.hint("merge"), u, "left_semi").withColumn(rank, F.row_number().over(W.partitionBy(u).orderBy("doc_id")))
    return once.filter(F.col(rank) == 1).select(*docs.columns)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that hold a passage of the benchmark.

    Null texts hold none and stay; repeated rows fare alike; an empty table or benchmark drops nothing.
    """
    arrow_rows(spark, TEXTS)
    d, t = _fresh(docs, "d"), _fresh(docs, "t")
    found = leaks(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet")).select(F.col("doc_id").alias(d), F.col("th").alias(t)).distinct()
    found = settle(found, "leaks")
    same = docs["doc_id"].cast("long").eqNullSafe(found[d]) & (F.xxhash64(F.coalesce(docs["text"], F.lit(""))) == found[t])
    return docs.join(found, same, "left_anti")


def redact_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replaces personal data in the texts; n_chars follows where there is such a column.

    A null text stays null; no row goes; repeated rows fare alike.
    """
    arrow_rows(spark, TEXTS)
    found = _fresh(docs, "found")
    text = F.col(found)["redacted"]
    changed = {"text": text}
    if "n_chars" in docs.columns:
        changed["n_chars"] = F.length(text).cast(docs.schema["n_chars"].dataType)
    told = docs.select("*", personal_data(trained_field())("text").alias(found))
    return told.select([changed[c].alias(c) if c in changed else F.col(c) for c in docs.columns])


def encode_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids and digests, one row a row; a null text has no ids."""
    arrow_rows(spark, TEXTS)
    return encode_documents(docs, public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), with_ids=True, kept_words=2 * KEPT_WORDS)


STAGES = [
    ("language_id", identify_language),
    ("near_dedup", drop_near_duplicates),
    ("decontaminate", drop_leaks),
    ("personal_data", redact_personal_data),
    ("bpe", encode_tokens),
]
ORACLE_SQL = None  # learnt models and a tokenizer decide; held against brute-force versions in tests/llm


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for name, stage in STAGES[:-1]:
        docs = settle(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
