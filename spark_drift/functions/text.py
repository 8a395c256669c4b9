"""Texts to features: tokens, light stemming, vocabulary, TF-IDF, a small SVD, topics."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.ml.clustering import LDA
from pyspark.ml.feature import IDF, CountVectorizer
from pyspark.ml.functions import vector_to_array
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: endings that are cut, longest first, per language (fixed values)
SUFFIXES = {
    "en": ("ing", "ies", "ed", "es", "s"),
    "fr": ("ement", "tion", "es", "e", "s"),
    "de": ("ungen", "ung", "en", "er", "e"),
    "es": ("ciones", "mente", "os", "as", "s"),
}


def tokens(text: Column, least: int = 2) -> Column:
    """Lower-case words of letters, in order, at least ``least`` letters long."""
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), "[^\\p{L}]+"), lambda w: F.char_length(w) >= least)


def stem(word: Column, lang: Column) -> Column:
    """The word without the first ending of its language that leaves three letters or more."""
    out = word
    for code, endings in SUFFIXES.items():
        cut = word
        for e in reversed(endings):
            cut = F.when(F.endswith(word, F.lit(e)) & (F.char_length(word) >= len(e) + 3), F.substr(word, F.lit(1), F.char_length(word) - len(e))).otherwise(cut)
        out = F.when(lang == code, cut).otherwise(out)
    return out


def terms(docs: DataFrame) -> DataFrame:
    """``doc_id, term, tf``."""
    words = docs.select("doc_id", F.explode(tokens(F.col("text"))).alias("term"))
    return words.groupBy("doc_id", "term").agg(F.count(F.lit(1)).alias("tf"))


def vocabulary(term_rows: DataFrame, size: int = 5000) -> DataFrame:
    """``term, df, total``: the ``size`` terms with most occurrences, ties by term."""
    by = term_rows.groupBy("term").agg(F.count(F.lit(1)).alias("df"), F.sum("tf").alias("total"))
    return by.orderBy(F.desc("total"), "term").limit(size)


def tf_idf(term_rows: DataFrame, words: DataFrame, docs: DataFrame) -> DataFrame:
    """``doc_id, term, tfidf`` with idf = log((N + 1) / (df + 1)). The vocabulary is
    bounded by its size, hence broadcast."""
    n = docs.agg(F.count(F.lit(1)).alias("n_docs"))
    weights = words.withColumn("j", F.lit(1)).join(n.withColumn("j", F.lit(1)), "j")
    weights = weights.select("term", F.log((F.col("n_docs") + 1) / (F.col("df") + 1)).alias("idf"))
    return term_rows.join(F.broadcast(weights), "term").select("doc_id", "term", (F.col("tf") * F.col("idf")).alias("tfidf"))


def keywords(weights: DataFrame, groups: DataFrame, group: str, k: int = 5) -> DataFrame:
    """``group, term, weight, rank``: the terms with the largest mean weight in each group."""
    sizes = groups.groupBy(group).agg(F.count(F.lit(1)).alias("size"))
    sums = weights.join(groups, "doc_id").groupBy(group, "term").agg(F.sum("tfidf").alias("s"))
    mean = sums.join(F.broadcast(sizes), group).select(group, "term", (F.col("s") / F.col("size")).alias("weight"))
    order = F.row_number().over(Window.partitionBy(group).orderBy(F.desc(F.round("weight", 9)), "term"))
    return mean.withColumn("rank", order).where(F.col("rank") <= k)


def vectors(docs: DataFrame, size: int = 5000) -> DataFrame:
    """``docs`` with sparse ``counts`` and ``tfidf`` vectors (library stages)."""
    rows = docs.withColumn("tokens_", tokens(F.col("text")))
    counts = CountVectorizer(inputCol="tokens_", outputCol="counts", vocabSize=size).fit(rows).transform(rows)
    return IDF(inputCol="counts", outputCol="tfidf").fit(counts).transform(counts).drop("tokens_")


BLOCK = 512


def _gram_times(sparse: DataFrame, q: np.ndarray) -> np.ndarray:
    """(A'A) q for the rows of sparse vectors: a partial product per task, summed by blocks
    of matrix rows on the executors; a matrix of the vocabulary's height comes back."""
    sent = sparse.sparkSession.sparkContext.broadcast(q)

    def partial(batches):
        q = sent.value
        total = np.zeros_like(q)
        for batch in batches:
            lists = batch.column(0).combine_chunks() if hasattr(batch.column(0), "combine_chunks") else batch.column(0)
            at = lists.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
            values = batch.column(1).flatten().to_numpy(zero_copy_only=False)
            sizes = np.array([len(x) if x is not None else 0 for x in lists.to_pylist()], dtype=np.int64)
            row = np.repeat(np.arange(len(sizes)), sizes)
            for k in range(q.shape[1]):
                y = np.bincount(row, values * q[at, k], len(sizes))
                total[:, k] += np.bincount(at, values * y[row], len(q))
        blocks = range(0, len(q), BLOCK)
        yield pa.RecordBatch.from_arrays(
            [pa.array([b // BLOCK for b in blocks], pa.int32()), pa.array([total[b : b + BLOCK].tobytes() for b in blocks], pa.binary())],
            names=["block", "part"],
        )

    def add(key, table):
        parts = [np.frombuffer(x, "<f8") for x in table.column("part").to_pylist()]
        return pa.table({"block": pa.array([key[0].as_py()], pa.int32()), "part": pa.array([np.sum(parts, axis=0).tobytes()], pa.binary())})

    schema = "block int, part binary"
    rows = sparse.mapInArrow(partial, schema).groupBy("block").applyInArrow(add, schema).collect()
    joined = b"".join(bytes(r["part"]) for r in sorted(rows, key=lambda r: r["block"]))
    return np.frombuffer(joined, "<f8").reshape(q.shape)


def right_vectors(rows: DataFrame, column: str, rank: int, passes: int = 5, extra: int = 10, seed: int = 0) -> np.ndarray:
    """First right singular vectors of the uncentred rows by subspace iteration; signs fixed."""
    plain = rows.select(F.unwrap_udt(column).alias("v")).select("v.size", "v.indices", "v.values")
    size = plain.agg(F.max("size")).first()[0]
    sparse = plain.where("indices is not null").select("indices", "values")
    q = np.linalg.qr(np.random.Generator(np.random.PCG64(seed)).normal(size=(size, min(size, rank + extra))))[0]
    for _ in range(passes):
        product = _gram_times(sparse, q)
        q, _ = np.linalg.qr(product)
    product = _gram_times(sparse, q)
    small = q.T @ product
    order = np.argsort(-np.linalg.eigvalsh((small + small.T) / 2))
    v = (q @ np.linalg.eigh((small + small.T) / 2)[1])[:, order[:rank]]
    return v * np.sign(v[np.abs(v).argmax(0), np.arange(v.shape[1])])


def reduce(rows: DataFrame, column: str = "tfidf", rank: int = 10) -> DataFrame:
    """``features``: the uncentred projection on the first right singular vectors."""
    from spark_drift.plans.lineage import cut

    rows = cut(rows)
    sent = rows.sparkSession.sparkContext.broadcast(right_vectors(rows, column, rank))

    @F.pandas_udf("array<double>")
    def onto(indices: pd.Series, values: pd.Series) -> pd.Series:
        v = sent.value
        return pd.Series([(np.asarray(b) @ v[np.asarray(a, dtype=np.int64)]).tolist() for a, b in zip(indices, values, strict=True)])

    parts = F.unwrap_udt(column)
    return rows.withColumn("features", onto(parts["indices"], parts["values"]))


def topics(rows: DataFrame, k: int = 10, seed: int = 1, rounds: int = 20, gap: float = 0.05) -> DataFrame:
    """``topic`` (largest share) and ``ambiguous`` (the runner-up is within ``gap``)."""
    model = LDA(k=k, seed=seed, maxIter=rounds, featuresCol="counts", topicDistributionCol="topics_").fit(rows)
    out = model.transform(rows).withColumn("shares_", vector_to_array("topics_"))
    top = F.sort_array("shares_", asc=False)
    best = F.array_position("shares_", F.array_max("shares_")).cast("int") - 1
    return out.withColumn("topic", best).withColumn("ambiguous", F.get(top, F.lit(0)) - F.get(top, F.lit(1)) < gap).drop("topics_", "shares_")


def without_tags(html: Column) -> Column:
    """Page text: scripts, styles and tags removed."""
    bare = F.regexp_replace(html, "(?is)<(script|style)[^>]*>.*?</\\1>", " ")
    return F.trim(F.regexp_replace(F.regexp_replace(bare, "<[^>]+>", " "), "\\s+", " "))
