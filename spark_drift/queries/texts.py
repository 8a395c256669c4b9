"""Texts to terms, weights and keywords."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spark_drift.functions import text
from spark_drift.queries.base import query, rounded, unit_sql
from spark_drift.sources.tables import read
from spark_drift.workloads import topics

TERMS_SQL = """tm as (select doc_id, term, count(*) as tf from (select doc_id, unnest(string_split_regex(lower(text), '[^\\p{L}]+')) as term from documents) where length(term) >= 2 group by 1, 2),
vo as (select term, count(*) as df, sum(tf) as total from tm group by 1 order by total desc, term limit 5000)"""


@query(f"with {TERMS_SQL} select doc_id, term, tf::bigint as tf from tm")
def tx_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return text.terms(read(spark, sf_dir, "documents"))


@query(f"with {TERMS_SQL} select term, df::bigint as df, total::bigint as total from vo")
def tx_vocab(spark: SparkSession, sf_dir: str) -> DataFrame:
    return text.vocabulary(text.terms(read(spark, sf_dir, "documents")))


IDF_SQL = f"{TERMS_SQL}, ti as (select doc_id, term, tf * ln(((select count(*) from documents) + 1) / (df + 1)::double) as tfidf from tm join vo using (term))"


@query(f"with {IDF_SQL} select doc_id, term, round(tfidf, 6) as tfidf from ti")
def tx_tfidf(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    rows = text.terms(docs)
    return rounded(text.tf_idf(rows, text.vocabulary(rows), docs), "tfidf")


@query(
    f"""with {IDF_SQL}, s as (select lang, term, sum(tfidf) / any_value(size) as weight from ti join documents using (doc_id) join (select lang, count(*) as size from documents group by 1) z using (lang) group by 1, 2),
k as (select *, row_number() over (partition by lang order by round(weight, 9) desc, term) as rank from s) select lang, term, round(weight, 6) as weight, rank::int as rank from k where rank <= 5"""
)
def tx_keywords(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    rows = text.terms(docs)
    weights = text.tf_idf(rows, text.vocabulary(rows), docs)
    return rounded(text.keywords(weights, docs.select("doc_id", "lang"), "lang"), "weight")


@query(
    f"""with e as (select *, case lang when 'fr' then 2005 when 'de' then 2010 when 'es' then 2014 else 2000 end as entry from documents)
select doc_id, lang, (entry + floor({unit_sql("'year:' || doc_id::varchar")} * (2019.999999::double - entry)))::int as year from e"""
)
def pseudo_years(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topics.pseudo_years(read(spark, sf_dir, "documents")).select("doc_id", "lang", "year")


@query("select page_id, length(trim(regexp_replace(regexp_replace(regexp_replace(html, '(?is)<script[^>]*>.*?</script>|<style[^>]*>.*?</style>', ' ', 'g'), '<[^>]+>', ' ', 'g'), '\\s+', ' ', 'g')))::bigint as chars from pages")
def tx_page_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "pages").select("page_id", F.char_length(text.without_tags(F.col("html"))).cast("long").alias("chars"))


@query()
def tx_svd(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topics.reduced(spark, sf_dir)


@query()
def tx_topics(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = text.vectors(read(spark, sf_dir, "documents").select("doc_id", "text"))
    return text.topics(rows, 10).select("doc_id", "topic", "ambiguous")


@query()
def tx_stems(spark: SparkSession, sf_dir: str) -> DataFrame:
    words = read(spark, sf_dir, "documents").select("lang", F.explode(text.tokens(F.col("text"))).alias("word"))
    return words.groupBy("lang", text.stem(F.col("word"), F.col("lang")).alias("stem")).agg(F.count(F.lit(1)).alias("n"))
