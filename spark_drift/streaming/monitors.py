"""Monitors on streams: windowed features, a micro-batch drift monitor, keyed state.

Timestamps without a zone are cast first, as watermarks need instants.
"""

from __future__ import annotations

import json
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from spark_drift.functions import numeric
from spark_drift.functions.numeric import Mixture, OnlineConfig
from spark_drift.operators import mixture
from spark_drift.operators.online import SERIES, Stepper

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(events: DataFrame, length: str, late: str | None = None) -> DataFrame:
    """``start, event_type, n, mean`` per tumbling window."""
    rows = events.withWatermark("ts", late) if late else events
    by = rows.groupBy(F.window("ts", length), "event_type").agg(F.count(F.lit(1)).alias("n"), F.avg("value").alias("mean"))
    return by.select(F.col("window.start").alias("start"), "event_type", "n", "mean")


def sliding(events: DataFrame, length: str, slide: str, late: str | None = None) -> DataFrame:
    rows = events.withWatermark("ts", late) if late else events
    by = rows.groupBy(F.window("ts", length, slide)).agg(F.count(F.lit(1)).alias("n"), F.avg("value").alias("mean"))
    return by.select(F.col("window.start").alias("start"), "n", "mean")


def sessions(events: DataFrame, gap: str, late: str | None = None) -> DataFrame:
    """``user_id, start, stop, n`` of bursts that end after a gap."""
    rows = events.withWatermark("ts", late) if late else events
    by = rows.groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return by.select("user_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("stop"), "n")


def fresh(events: DataFrame, late: str) -> DataFrame:
    """Replayed event ids dropped within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


class BatchMonitor:
    """``foreachBatch`` target for thin streams: one drift step per micro-batch on the driver,
    replays skipped by batch id. A micro-batch above ``max_rows`` is refused; streams with
    such batches take ``StepwiseMonitor``."""

    def __init__(
        self, train: np.ndarray, features: list[str], cfg: OnlineConfig | None = None, sink: Callable[[dict], None] | None = None, max_rows: int = 100_000
    ) -> None:
        self.cfg, self.features, self.sink, self.max_rows = cfg or OnlineConfig(), features, sink, max_rows
        self.monitor = numeric.Monitor(train, self.cfg)
        self.last, self.rows = -1, []

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id <= self.last:
            return
        taken = batch.select(*self.features).limit(self.max_rows + 1).collect()
        if len(taken) > self.max_rows:
            raise ValueError(f"a micro-batch of more than {self.max_rows} rows: use StepwiseMonitor")
        x = np.array([[float(v) for v in r] for r in taken]).reshape(-1, len(self.features))
        self.last = batch_id
        if not len(x):
            return
        x = x[np.lexsort(x.T[::-1])]
        self.monitor.arrive(x, batch_id, len(x))
        value, _ = self.monitor.degree()
        row = {"t": batch_id, "n": len(x), "degree": value, "components": len(self.monitor.mix.ids)}
        self.rows.append(row)
        if self.sink:
            self.sink(row)


class StepwiseMonitor:
    """``foreachBatch`` target for batches of any size: each is one distributed step.

    With ``state_path`` the components, the pool and what was reported are written after
    each batch, in a folder of its number and marked complete last; a monitor made anew on
    that path goes on from the newest complete folder, and batches it has seen are skipped.
    """

    def __init__(
        self, train: DataFrame, features: list[str], cfg: OnlineConfig | None = None, state_path: str | None = None,
        sink: Callable[[dict], None] | None = None,
    ) -> None:
        self.path, self.sink, self.last, self.rows = state_path, sink, -1, []
        found = self._newest(train.sparkSession) if state_path else None
        if found is None:
            self.stepper = Stepper(train, features, cfg)
            return
        spark = train.sparkSession
        home, self.last = found
        self.stepper = Stepper(train, features, cfg, mixture.from_table(spark.read.parquet(f"{home}/components")))
        pool = spark.read.parquet(f"{home}/pool")
        self.stepper.pool = pool if not pool.isEmpty() else None
        series = spark.read.schema(SERIES).parquet(f"{home}/series").orderBy("t")
        self.rows = [r.asDict() for r in series.collect()]

    def _newest(self, spark: SparkSession) -> tuple[str, int] | None:
        root = spark._jvm.org.apache.hadoop.fs.Path(self.path)
        fs = root.getFileSystem(spark._jsc.hadoopConfiguration())
        if not fs.exists(root):
            return None
        names = [s.getPath().getName() for s in fs.listStatus(root)]
        done = [int(n) for n in names if n.isdigit() and fs.exists(spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{n}/series/_SUCCESS"))]
        return (f"{self.path}/{max(done)}", max(done)) if done else None

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id <= self.last:
            return
        row = self.stepper.step(batch, batch_id)
        self.last = batch_id
        if row is None:
            return
        self.rows.append(dict(zip([c.split()[0] for c in SERIES.split(", ")], row, strict=True)))
        if self.path:
            self._save(batch.sparkSession, f"{self.path}/{batch_id}")
        if self.sink:
            self.sink(self.rows[-1])

    def _save(self, spark: SparkSession, home: str) -> None:
        s = self.stepper
        mixture.table(spark, s.mix).write.mode("overwrite").parquet(f"{home}/components")
        pool = s.pool if s.pool is not None else s.ref.select(*s.features).limit(0)
        pool.write.mode("overwrite").parquet(f"{home}/pool")
        spark.createDataFrame([tuple(r.values()) for r in self.rows], SERIES).coalesce(1).write.mode("overwrite").parquet(f"{home}/series")


STATE = "n double, mean string, cov string, ref string"
OUTPUT = "key string, seen long, degree double"


def keyed_monitor(events: DataFrame, key: str, features: list[str], train_rows: int = 200) -> DataFrame:
    """One independent monitor per key in the state store.

    A key's first ``train_rows`` rows become its reference; later batches are compared with
    it. The state holds the reference and its Gaussian summary, bounded by ``train_rows``.
    """
    d = len(features)

    def step(k: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        ref = np.array(json.loads(state.get[3])) if state.exists else np.zeros((0, d))
        n = state.get[0] if state.exists else 0.0
        x = np.concatenate([b[features].to_numpy(float) for b in batches])
        x = x[np.lexsort(x.T[::-1])]
        take = max(0, train_rows - len(ref))
        ref, x = np.concatenate([ref, x[:take]]), x[take:]
        cov = np.cov(ref.T, bias=True).reshape(d, d) if len(ref) > 1 else np.eye(d)
        state.update((n + take + len(x), json.dumps(ref.mean(0).tolist()), json.dumps(cov.tolist()), json.dumps(ref.tolist())))
        degree = None
        if len(x):
            mix = Mixture(np.array([0]), np.array([float(len(ref))]), ref.mean(0)[None], cov[None])
            degree = numeric.component_degree(ref, np.zeros(len(ref), int), x, mix.ids[np.zeros(len(x), int)])[0]
        yield pd.DataFrame({"key": [str(k[0])], "seen": [int(n + take + len(x))], "degree": [degree]})

    return events.groupBy(key).applyInPandasWithState(step, OUTPUT, STATE, "update", GroupStateTimeout.NoTimeout)


def with_components(stream: DataFrame, components: DataFrame, on: list[str]) -> DataFrame:
    """Arriving rows with static component rows (a small table, one row per component)."""
    return stream.join(F.broadcast(components), on)
