"""Streaming upkeep of what fits need: anchor sums, windows of response rates, deduplicated rows, panels in flight, online steps."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from gradvb.designs import indicator
from gradvb.families import Gaussian, NormalPrior
from gradvb.fit import FitConfig, ascend
from gradvb.models import Logit, Model
from gradvb.sums import Sums, sum_expressions


def event_stream(stream: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Events as design rows with an event time that watermarks accept."""
    return (
        stream.withColumn("time", F.col("ts").cast("timestamp"))
        .withWatermark("time", delay)
        .select(
            "event_id", "user_id", "time", "event_type", "value", indicator(F.col("event_type") == "purchase").cast("double").alias("y"), F.lit(1.0).alias("x0"),
            indicator((F.hour("time") < 6) | (F.hour("time") >= 22)).cast("double").alias("x1"), indicator(F.dayofweek("time").isin(1, 7)).cast("double").alias("x2"), (F.col("value") / 100).alias("x3"),
        )
    )


def streaming_anchor_sums(rows: DataFrame, theta, model: Model | None = None) -> DataFrame:
    """n and the anchor's sums so far; additive, so every trigger adds its rows (complete mode)."""
    return rows.groupBy().agg(*sum_expressions(model or Logit(), theta, 2))


def windowed_rates(rows: DataFrame, length: str = "1 day", slide: str | None = None) -> DataFrame:
    """Rows, responses and their rate by tumbling or sliding windows."""
    window = F.window("time", length, slide) if slide else F.window("time", length)
    return rows.groupBy(window.alias("w")).agg(F.count("*").alias("n"), F.sum("y").alias("ones")).select(F.col("w.start").alias("start"), "n", "ones", (F.col("ones") / F.col("n")).alias("rate"))


def session_rates(rows: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return rows.groupBy("user_id", F.session_window("time", gap).alias("w")).agg(F.count("*").alias("n"), F.sum("y").alias("ones")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", "ones")


def deduplicated(rows: DataFrame, keys: tuple[str, ...] = ("event_id",)) -> DataFrame:
    return rows.dropDuplicatesWithinWatermark(list(keys))


def with_dimension(rows: DataFrame, table: DataFrame, on: str) -> DataFrame:
    """Stream-static join."""
    return rows.join(table, on, "left")


def matched_streams(left: DataFrame, right: DataFrame, seconds: int = 3600) -> DataFrame:
    """Stream-stream interval join by user: right rows within ``seconds`` after left ones.

    Rows meet by user and span of ``seconds``: a right row lies in one span, its left rows in that or the one before, so each pair comes out once.
    """
    span = lambda time: F.floor(F.unix_seconds(time) / F.lit(seconds)).cast("long")
    a = left.select(F.col("user_id"), F.col("time").alias("left_time"), F.col("event_id").alias("left_id"))
    a = a.withColumn("span", F.explode(F.array(span(F.col("left_time")), span(F.col("left_time")) + 1)))
    b = right.select(F.col("user_id").alias("right_user"), F.col("time").alias("right_time"), F.col("event_id").alias("right_id"), span(F.col("time")).alias("right_span"))
    close = (F.col("user_id") == F.col("right_user")) & (F.col("span") == F.col("right_span")) & (F.col("right_time") >= F.col("left_time")) & (F.col("right_time") <= F.col("left_time") + F.expr(f"INTERVAL {seconds} SECONDS"))
    return a.join(b, close).drop("right_user", "span", "right_span")


def panel_buffer(rows: DataFrame) -> DataFrame:
    """Per user, rows and responses seen so far, kept as state."""

    def update(key: tuple, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n, ones = state.get if state.exists else (0, 0.0)
        for part in parts:
            n, ones = n + len(part), ones + float(part["y"].sum())
        state.update((n, ones))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "ones": [ones]})

    return rows.select("user_id", "y").groupBy("user_id").applyInPandasWithState(update, "user_id long, n long, ones double", "n long, ones double", "update", "NoTimeout")


def run_to_end(frame: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None) -> StreamingQuery:
    """Run what is available into a memory table and stop."""
    writer = frame.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True)
    query = (writer.option("checkpointLocation", checkpoint) if checkpoint else writer).start()
    query.awaitTermination()
    return query


#: Settings of a stream whose state grows with its input: RocksDB holds it on disk, within so many MB of memory an executor.
DISK_STATE = {
    "spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider",
    "spark.sql.streaming.stateStore.rocksdb.boundedMemoryUsage": "true",
    "spark.sql.streaming.stateStore.rocksdb.maxMemoryUsageMB": "256",
}


def run_to_table(frame: DataFrame, path: str, checkpoint: str, state: dict[str, str] = DISK_STATE) -> DataFrame:
    """Run what is available into files under ``path`` (append mode) and read them back: rows never go to the driver, and ``state`` says where state is held."""
    spark = frame.sparkSession
    before = {name: spark.conf.get(name, None) for name in state}
    for name, value in state.items():
        spark.conf.set(name, value)
    try:
        query = frame.writeStream.format("parquet").outputMode("append").option("checkpointLocation", checkpoint).trigger(availableNow=True).start(path)
    finally:
        for name, value in before.items():
            spark.conf.unset(name) if value is None else spark.conf.set(name, value)
    query.awaitTermination()
    return spark.read.schema(frame.schema).parquet(path)


def to_batches(frame: DataFrame, sink: Callable[[DataFrame, int], None], checkpoint: str | None = None) -> StreamingQuery:
    writer = frame.writeStream.foreachBatch(sink).trigger(availableNow=True)
    query = (writer.option("checkpointLocation", checkpoint) if checkpoint else writer).start()
    query.awaitTermination()
    return query


class OnlineFit:
    """One natural step for each mini-batch, with sums kept up at a fixed anchor (a heuristic: early rows weigh in every step)."""

    def __init__(self, state: Gaussian, theta: np.ndarray, model: Model | None = None, prior: NormalPrior | None = None, cfg: FitConfig | None = None) -> None:
        self.state, self.theta, self.model, self.prior, self.cfg = state, np.asarray(theta, float), model or Logit(), prior or NormalPrior(), cfg or FitConfig(s=64, max_iter=1).settled()
        d = len(self.theta)
        self.sums, self.steps = Sums(self.theta, 0, 0.0, np.zeros(d), np.zeros((d, d))), 0

    def __call__(self, batch: DataFrame, epoch: int) -> None:
        from gradvb.estimators import Estimate, assemble
        from gradvb.sums import exact_sums

        new = exact_sums(batch, self.theta, self.model)
        if not new.n:
            return
        old = self.sums
        self.sums = Sums(self.theta, old.n + new.n, old.loglik + new.loglik, old.grad + new.grad, old.hess + new.hess)
        sums = self.sums

        class Expansion:
            n = sums.n

            @staticmethod
            def estimate(thetas: np.ndarray, iteration: int) -> Estimate:
                grad, ll = assemble(thetas, sums, np.zeros_like(thetas), np.zeros(len(thetas)), "linear")
                return Estimate(grad, ll, 0.0, new.n)

        self.state = ascend(Expansion, self.state, self.prior, self.cfg).state
        self.steps += 1
