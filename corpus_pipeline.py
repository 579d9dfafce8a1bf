"""A training-data pipeline of five stages over ``documents``.

Every stage takes (spark, docs, sf_dir), works on all rows that the stage before it kept, and returns a DataFrame that is
written as Parquet and read again for the next one. All but the last return the columns that they were given.

1. language_id   drops texts without a letter and those that no language fits (score under REJECT_BELOW)
2. exact_dedup   keeps the row with the largest doc_id of equal texts
3. simhash       keeps the row with the smallest doc_id of each component of near-duplicates
4. mixing        draws sources towards target weights within a token budget, without repeating rows
5. byte_bpe      encodes and decodes what is left: doc_id, n_tokens, ids_sha256, decoded_sha256

Stages that drop rows keep null ids and repeated rows apart by content; an empty table passes through.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from obljoin.llm import langid, mixing
from obljoin.llm.bpe import token_digests
from obljoin.llm.common import saved, table
from obljoin.llm.exact_dedup import deduplicated
from obljoin.llm.simhash import one_of_each

#: With four languages a score of 0.25 means nothing is known; short clean texts stay well above this.
REJECT_BELOW = 0.3
#: Share of all words that the mix takes.
MIX_SHARE = 0.8


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = langid.train(docs, F.lit(True))
    judged = langid.identify(docs, model, whole=True)
    fits = (F.col("lang_pred") != langid.UNKNOWN) & (F.col("score") >= REJECT_BELOW)
    return judged.where(fits).select("row.*")


def exact_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return deduplicated(docs)


def simhash(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return one_of_each(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    levels, weights = mixing.document_tree()
    return mixing.mix(docs, levels, weights, budget=MIX_SHARE, max_epochs=1, seed=8, counts=False)


def byte_bpe(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ranks = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
    return saved(token_digests(docs, ranks)).select("doc_id", "n_tokens", "ids_sha256", "decoded_sha256")


STAGES = [
    ("language_id", language_id),
    ("exact_dedup", exact_dedup),
    ("simhash", simhash),
    ("mixing", mix_sources),
    ("byte_bpe", byte_bpe),
]

#: Classifiers, fingerprints and merges are beyond SQL; tests compare the stages with plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES:
        docs = saved(stage(spark, docs, sf_dir))
    return docs
