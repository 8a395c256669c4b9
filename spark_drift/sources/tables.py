"""Reading feature tables and writing results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def features(df: DataFrame, columns: list[str], nulls: str = "error") -> DataFrame:
    """``df`` with the columns as doubles. ``nulls``: ``error`` raises on the first missing
    or NaN value when read, ``drop`` leaves its row out, ``mean`` puts the mean in."""
    cast = df.withColumns({c: F.col(c).cast("double") for c in columns})
    bad = None
    for c in columns:
        one = F.col(c).isNull() | F.isnan(c)
        bad = one if bad is None else bad | one
    if nulls == "drop":
        return cast.where(~bad)
    if nulls == "mean":
        good = cast.agg(*[F.avg(F.when(~F.isnan(c), F.col(c))).alias(c) for c in columns]).first()
        return cast.withColumns({c: F.when(F.col(c).isNull() | F.isnan(c), F.lit(good[c])).otherwise(F.col(c)) for c in columns})
    check = F.when(bad, F.raise_error(F.lit("a feature is null or NaN"))).otherwise(F.lit(True))
    return cast.where(check)


def standardise(df: DataFrame, columns: list[str], train: DataFrame | None = None) -> DataFrame:
    """z-scores by the training rows' mean and deviation; no spread gives 0."""
    stats = (train if train is not None else df).agg(
        *[F.avg(c).alias(f"m_{c}") for c in columns], *[F.stddev_pop(c).alias(f"s_{c}") for c in columns]
    )
    joined = df.withColumn("j_", F.lit(1)).join(F.broadcast(stats.withColumn("j_", F.lit(1))), "j_")
    z = {c: F.when(F.col(f"s_{c}") > 0, (F.col(c) - F.col(f"m_{c}")) / F.col(f"s_{c}")).otherwise(0.0) for c in columns}
    return joined.withColumns(z).select(*df.columns)


def write_parts(df: DataFrame, path: str, by: list[str]) -> None:
    """Parquet partitioned by time or component, replacing the partitions written."""
    df.repartition(*by).sortWithinPartitions(*by).write.mode("overwrite").partitionBy(*by).parquet(path)


def payload(df: DataFrame) -> DataFrame:
    """One JSON document per row, for a front end."""
    return df.select(F.to_json(F.struct("*")).alias("json"))


def rows(spark: SparkSession, path: str, schema: str, kind: str = "parquet", stream: bool = False, files_per_trigger: int = 100) -> DataFrame:
    """Rows of ``parquet``, ``csv`` (with a header) or ``json`` files under a stated schema.

    The schema is never inferred, so no pass is spent on it and a batch and a stream agree;
    a value that does not fit its type is null in text formats.
    """
    if kind not in ("parquet", "csv", "json"):
        raise ValueError(f"unknown kind of file: {kind}")
    reader = spark.readStream.option("maxFilesPerTrigger", files_per_trigger) if stream else spark.read
    if kind == "csv":
        reader = reader.option("header", True).option("escape", '"')
    return reader.schema(schema).format(kind).load(path)


def ticks(spark: SparkSession, rows_per_second: int = 10) -> DataFrame:
    """A stream ``t, i`` at a steady rate, to drive demonstrations and load tests."""
    rate = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    return rate.select(F.col("timestamp").alias("t"), F.col("value").alias("i"))


def append_parts(stream: DataFrame, path: str, checkpoint: str, by: list[str]):
    """A started query that appends a stream to Parquet, partitioned, each row once; it takes
    what there is and stops, so that a scheduler can call it again."""
    return stream.writeStream.partitionBy(*by).option("checkpointLocation", checkpoint).trigger(availableNow=True).start(path, "parquet", "append")
