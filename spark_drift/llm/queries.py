"""The ten operators as registered queries, with production parameters on whole tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spark_drift.llm import (
    bpe,
    chat_format,
    fingerprints,
    language_id,
    line_dedup,
    mixing,
    quality_classifier,
    quality_rules,
    samples,
    simhash,
    toxicity,
)
from spark_drift.plans.lineage import cut


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    out = samples.held_out(F.col("doc_id"), 4, 2)
    lean = docs.select("doc_id", "text", "lang")
    prototypes = language_id.fit_prototypes(lean.where(~out))
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), out.alias("held_out"), "text")
    return language_id.predict(keyed, prototypes, ["doc_id", "held_out"])


def op2_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat_format.digests(chat_format.with_planted(spark, table(spark, sf_dir, "conversations")))


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    trees = quality_rules.fit_rules(docs, table(spark, sf_dir, "labels"))
    return quality_rules.judge(docs, trees)


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return toxicity.score_documents(docs, toxicity.fit_toxicity(docs, table(spark, sf_dir, "labels")))


def op5_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(table(spark, sf_dir, "documents"))
    fingerprint = F.lower(F.lpad(F.hex("fp"), 16, "0"))
    return found.select("doc_id", fingerprint.alias("fingerprint"), "component_id")


def op6_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return quality_classifier.score_documents(docs, quality_classifier.fit_quality(docs, table(spark, sf_dir, "labels")))


def op7_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return bpe.encode_documents(keyed, ["doc_id"], with_ids=False)


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    # one scan of the texts; what follows needs ids, sources and sizes only
    return mixing.mix(cut(mixing.sized(table(spark, sf_dir, "documents")))).drop("source")


def op9_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints.neighbour_likeness(table(spark, sf_dir, "documents"))


def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    kept = line_dedup.kept_lines(docs)
    return kept.select(
        F.col("row.doc_id").alias("doc_id"),
        F.col("added.n_lines").alias("n_lines"),
        F.col("added.n_dropped").alias("n_dropped"),
        F.sha2(F.col("added.kept_text").cast("binary"), 256).alias("kept_sha256"),
    )


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {
    f.__name__: f
    for f in (
        op1_language_id,
        op2_chat_format,
        op3_quality_rules,
        op4_toxicity,
        op5_simhash,
        op6_quality_classifier,
        op7_bpe,
        op8_mixing,
        op9_fingerprints,
        op10_line_dedup,
    )
}

LINES_SQL = r"""
with d as (select doc_id, text, row_number() over () as r from documents),
l as (select r, doc_id, coalesce(doc_id::varchar, 'text ' || md5(text)) as document, u.line, u.pos
  from d, unnest(string_split(coalesce(text, ''), chr(10))) with ordinality as u(line, pos)),
k as (select r, doc_id, document, line, pos,
  translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
    'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as key from l),
c as (select key from k where key <> '' group by key having count(distinct document) >= 10),
m as (select k.*, c.key is not null as gone from k left join c using (key))
select any_value(doc_id) as doc_id, count(*)::bigint as n_lines, count(*) filter (where gone)::bigint as n_dropped,
  sha256(coalesce(string_agg(line, chr(10) order by pos) filter (where not gone), '')) as kept_sha256
from m group by r
"""

ORACLES = {
    "op2_chat_format": chat_format.oracle(),
    "op8_mixing": mixing.oracle(),
    "op10_line_dedup": LINES_SQL,
}
