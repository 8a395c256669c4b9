"""A corpus pipeline over ``documents``: rules, line dedup, near dedup, mixing, encoding.

Each stage takes ``(spark, docs, sf_dir)`` and works on all that its predecessor kept;
its result is written as Parquet and read again as the next stage's ``docs``. All stages take
an empty table (and the first one empty ``labels``), nulls in any column, texts of any
length, repeated rows and further columns; what each makes of them is said with it.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from spark_drift.llm import bpe, line_dedup, mixing, quality_rules, simhash
from spark_drift.plans.lineage import ensure_checkpoint_dir


def quality_rules_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the limits or the trees reject go.

    A null or empty text has no words and goes; repeated rows share one verdict; a row without an id is
    judged like any other; without labels the limits alone judge. A score at the threshold stays."""
    trees = quality_rules.fit_rules(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return quality_rules.keep_good(docs, trees)


def line_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines found in ten different texts or more go; ``n_chars`` follows the text.

    Exact copies count once, or a group of ten would lose all its text before the next stage
    keeps one of it. Rows stay, those without a line left with the empty text; a null text becomes empty."""
    return line_dedup.drop_common_lines(docs, per="text")


def near_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays: linked by the fingerprints, or by five-word
    shingles with a Jaccard similarity of 0.8 or more.

    The smallest id stays, of equal ids the smallest text digest, of repeated rows one; null and empty
    texts form one group; rows without an id cannot be named and all stay."""
    return simhash.keep_similar_one(docs, RADIUS)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows repeat by their copies in the mix; those with none go.

    A row without words is worth no tokens and has as many copies as its cell's rate gives; a null source is
    a source of its own; equal sizes are told apart by a digest of id and text."""
    return mixing.mixed_documents(docs)


def encoding_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each row's text, with digests of the ids and of the text decoded from them.

    Null and empty texts have no ids; repeated rows repeat; rows without an id keep none."""
    return bpe.encode_documents(docs, ["doc_id", "source"])


#: differing bits of the three-word fingerprints that link two documents
RADIUS = 4

STAGES = [
    ("quality_rules", quality_rules_stage),
    ("line_dedup", line_dedup_stage),
    ("near_dedup", near_dedup_stage),
    ("mixing", mixing_stage),
    ("encoding", encoding_stage),
]

#: boosted trees, SimHash and byte-pair encoding have no SQL form
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; what they write stays in the shared checkpoint folder."""
    home = f"{ensure_checkpoint_dir(spark)}/corpus-{uuid.uuid4().hex}"
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{home}/{name}")
        docs = spark.read.parquet(f"{home}/{name}")
    return docs
