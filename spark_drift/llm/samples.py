"""Bounded labelled samples for models that are fitted on the driver."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def fold(doc_id: Column, parts: int) -> Column:
    """crc32 of the id's text, modulo ``parts``; null for a null id."""
    return F.crc32(doc_id.cast("string").cast("binary")) % parts


def held_out(doc_id: Column, parts: int, part: int) -> Column:
    return F.coalesce(fold(doc_id, parts) == part, F.lit(False))


def drawn(ids: DataFrame, limit: int, salt: str) -> DataFrame:
    """``limit`` rows at most, those with the smallest digests of ``doc_id``."""
    return ids.orderBy(F.xxhash64(F.col("doc_id").cast("string"), F.lit(salt)), "doc_id").limit(limit)


#: text that a fit may draw altogether
SAMPLE_BYTES = 64 << 20


def bounded(docs: DataFrame, ids: DataFrame, salt: str, most_bytes: int = SAMPLE_BYTES) -> DataFrame:
    """``ids`` (``doc_id`` and other columns, bounded in number) with ``text``, one row per id.

    Of rows that share an id the one with the smallest text digest counts. Ids are taken
    in the order of their digests for as long as their texts together hold ``most_bytes``
    at most (the first always), so what reaches the driver is bounded in bytes too.
    """
    plain = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    plain = plain.withColumn("digest", F.xxhash64("text"))
    lean = plain.join(F.broadcast(ids.select("doc_id")), "doc_id").groupBy("doc_id").agg(
        F.min(F.struct("digest", F.coalesce(F.octet_length("text"), F.lit(0)).alias("bytes"))).alias("one")
    )
    # one row per drawn id, hence a bounded window
    order = Window.orderBy(F.xxhash64(F.col("doc_id").cast("string"), F.lit(salt)), "doc_id").rowsBetween(Window.unboundedPreceding, -1)
    before = F.coalesce(F.sum("one.bytes").over(order), F.lit(0))
    lean = lean.withColumn("before", before).where((F.col("before") == 0) | (F.col("before") + F.col("one.bytes") <= most_bytes))
    chosen = ids.join(lean.select("doc_id", F.col("one.digest").alias("digest")), "doc_id")
    return plain.join(F.broadcast(chosen), ["doc_id", "digest"]).dropDuplicates(["doc_id"]).drop("digest")


def labelled(
    docs: DataFrame, labels: DataFrame, column: str, limit: int, parts: int = 0, part: int = -1, most_bytes: int = SAMPLE_BYTES
) -> DataFrame:
    """``doc_id, y, text`` of at most ``limit`` labelled documents outside the held-out fold.

    Repeated labels of one id count once (the largest), and so do its documents; rows whose
    label or id is null are left out. The id list is bounded by ``limit``, hence broadcast.
    """
    good = labels.where(F.col(column).isNotNull() & F.col("doc_id").isNotNull())
    if parts:
        good = good.where(~held_out(F.col("doc_id"), parts, part))
    ids = good.groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max(column).cast("int").alias("y"))
    return bounded(docs, drawn(ids, limit, column), column, most_bytes)
