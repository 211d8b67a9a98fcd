"""Corpus preparation: quality, exact copies, near copies, mixture, packing.

Every stage is (name, function); a function takes (spark, docs, sf_dir) and returns a DataFrame, which is written and read
again as the next one's docs. All but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from sieveset.llm import exact_dedup, mixing, packing, quality, simhash
from sieveset.llm.common import materialise, table

#: Near copies: five words to a shingle, Jaccard similarity of the sets of shingles 0.8 or more.
SHINGLE_WORDS, SIMILARITY = 5, (4, 5)


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rule ensemble rejects go."""
    return quality.keep_good(docs, table(spark, sf_dir, "labels"))


def exact_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the row with the largest doc_id stays."""
    return exact_dedup.drop_copies(docs)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays: SimHash fingerprints meet at covering-code anchors, whole sets of shingles decide."""
    return simhash.drop_similar(docs, words=SHINGLE_WORDS, limit=SIMILARITY)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents by target weights of domain, language and source; one that two epochs take comes twice."""
    columns = docs.columns
    return mixing.mix(mixing.with_domain(docs)).select(*columns)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sequences of at most 4096 tokens. Workers come here with what the stages before left in memory, so they take the lean setting."""
    return packing.pack(docs, slice_docs=200, cache_words=50_000)


STAGES = [
    ("quality", quality_stage),
    ("exact_dedup", exact_stage),
    ("near_dedup", near_stage),
    ("mixing", mixing_stage),
    ("packing", packing_stage),
]

#: Stages run trained models, tokenizers and 64-bit sketches, which SQL can't express.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``documents`` through all stages."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
