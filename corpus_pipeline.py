"""The corpus pipeline: five stages of the operators in curvature_spark.llm, documents in, packed pieces out.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; it is written as Parquet and read again as the
next stage's docs. When a stage begins, its predecessor's result has been written, so the intermediate
tables of the stages before are deleted then.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from curvature_spark.llm import jaccard, mixing, naming, packing, toxicity
from curvature_spark.llm.queries import vocabulary
from curvature_spark.plans.cuts import release, written
from curvature_spark.sources.catalog import load

OWNER = "pipeline"


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose toxicity score stays below one half."""
    release(OWNER)
    return toxicity.clean_documents(docs, load(spark, sf_dir, "labels"), owner=OWNER)


def drop_exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of texts equal but for the case of A to Z: the one of largest doc_id."""
    release(OWNER)
    return naming.deduplicated(docs, owner=OWNER)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component of similarity 0.8 or more on five-word shingles: the one of smallest doc_id."""
    release(OWNER)
    return jaccard.one_of_each_group(docs, n=5, num=4, den=5, owner=OWNER)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them."""
    release(OWNER)
    return mixing.mixed_documents(docs, owner=OWNER)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of token sequences."""
    import public_tokenizers

    release(OWNER)
    return packing.packed(docs, vocabulary("byte_bpe_50k.json"), vocabulary("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


STAGES = [
    ("toxicity", drop_toxic),
    ("exact dedup", drop_exact_copies),
    ("near duplicates", drop_near_copies),
    ("source mix", mix_sources),
    ("packing", pack_sequences),
]

#: Packing has no SQL form; tests hold run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages over `documents`, each but the last written and read again; a stage's table goes when the next one's is there."""
    docs, before = load(spark, sf_dir, "documents"), None
    for number, (_, stage) in enumerate(STAGES[:-1]):
        mine = f"{OWNER}-{uuid.uuid4().hex}"
        docs = written(stage(spark, docs, sf_dir), f"stage-{number}", mine)
        if before:
            release(before)
        before = mine
    return STAGES[-1][1](spark, docs, sf_dir)
