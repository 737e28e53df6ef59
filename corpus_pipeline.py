"""Five stages from raw documents to token ids; each stage's rows are written as Parquet and read again for the next.

Quality rules, toxicity, near-duplicates and mixing return the columns of documents and drop rows; the last stage
returns the token ids of every document that is left, with digests of the ids and of the bytes decoded from them.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from linseg.llm import bpe, mixing, neardup, quality, toxicity
from linseg.llm.common import ensure_checkpoint_dir, load


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps what the line field and the base rule accept."""
    return quality.keep_good(docs, quality.fit(docs, load(spark, sf_dir, "labels")))


def toxicity_filter(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps what the lexicon doesn't predict toxic."""
    return toxicity.keep_clean(docs, toxicity.fit(docs, load(spark, sf_dir, "labels")))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps of each group of similar shingle sets the document of least id."""
    return neardup.keep_one(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Samples by calibrated probabilities towards tempered marginals."""
    return mixing.sample(docs)


def encode_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, digests and token_ids; the words known to a worker take less room than alone and go with the task, for earlier stages' workers may still be there."""
    return bpe.encode(docs, *bpe.default_vocabulary(), cache=bpe.KNOWN_BYTES, keep=False)


STAGES = [
    ("quality_rules", quality_rules),
    ("toxicity", toxicity_filter),
    ("near_duplicates", near_duplicates),
    ("mixing", mix_sources),
    ("byte_bpe", encode_tokens),
]

#: Viterbi decoding, automata and shingle similarity can't be said in SQL; tests/llm compare the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    folder = f"{ensure_checkpoint_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
    return docs
