"""Streams over ``events``: windows with watermarks, stateful statistics, scoring against a model table, incremental training."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coordloom.operators import blocks
from coordloom.operators.solvers import FitResult, Model, TrainSpec, fit
from coordloom.storage import shared_dir


def event_stream(spark: SparkSession, path: str) -> DataFrame:
    """The parquet files under ``path`` as a stream, with ts as a timestamp."""
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def windowed(events: DataFrame, length: str = "1 hour", slide: str | None = None, late: str = "2 hours") -> DataFrame:
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    if events.isStreaming:
        events = events.withWatermark("ts", late)
    return events.groupBy(w.alias("w")).agg(F.count("*").alias("n"), F.count_if(F.col("event_type") == "purchase").alias("n_purchase")).select(F.col("w.start").alias("start"), "n", "n_purchase")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    if events.isStreaming:
        events = events.withWatermark("ts", late)
    return events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def dedup(events: DataFrame, late: str = "2 hours") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else events.dropDuplicates(["event_id"])


def scored(events: DataFrame, model: DataFrame) -> DataFrame:
    """Stream-static join with a model table (event_type, weight)."""
    return events.join(model, "event_type").withColumn("score", F.col("weight") * F.col("value"))


def user_statistics(events: DataFrame) -> DataFrame:
    """Running count and mean of ``value`` per user, kept as state between batches."""

    def update(key: tuple, frames: Iterator, state) -> Iterator:
        import pandas as pd

        n, total = state.get if state.exists else (0, 0.0)
        for frame in frames:
            n, total = n + len(frame), total + float(frame["value"].sum())
        state.update((n, total))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "mean": [total / max(1, n)]})

    keyed = events.select("user_id", "value")
    return keyed.groupBy("user_id").applyInPandasWithState(update, "user_id long, n long, mean double", "n long, total double", "update", "NoTimeout")


def run_available(df: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a stream over what is there into files of the shared folder and give back the result. Each batch is a folder; in mode
    ``complete`` the last one is the result, otherwise all of them."""
    spark, out = df.sparkSession, shared_dir(df.sparkSession, f"stream-{name}")
    written: list[int] = []

    def store(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={batch_id}")  # a batch that is repeated replaces itself
        written.append(batch_id)

    q = df.writeStream.foreachBatch(store).outputMode(mode).option("checkpointLocation", f"{out}-log").trigger(availableNow=True).start()
    q.awaitTermination()
    if not written:
        return spark.createDataFrame([], df.schema)
    paths = [f"{out}/batch={k}" for k in (sorted(set(written)) if mode != "complete" else [max(written)])]
    return spark.read.schema(df.schema).parquet(*paths)


class IncrementalTrainer:
    """foreachBatch: new examples join the data with alpha 0 and training goes on from the model at hand.

    Each batch is one more set of blocks behind the others, so old block numbers and alphas stay valid.
    """

    def __init__(self, d: int, spec: TrainSpec, bucket: int = 8, epochs: int = 1):
        self.d, self.spec, self.bucket, self.epochs = d, spec, bucket, epochs
        self.frames: list[DataFrame] = []
        self.n = self.n_blocks = 0
        self.result: FitResult | None = None

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        from coordloom.sources.ids import densify

        rows = densify(batch, ["eid"], "_e").drop("eid").withColumnRenamed("_e", "eid")
        n = rows.count()
        if not n:
            return
        new = blocks.pack(rows, n, self.d, self.bucket, 1)
        self.frames.append(new.frame.withColumn("bid", F.col("bid") + self.n_blocks))
        self.n, self.n_blocks = self.n + n, self.n_blocks + new.n_blocks
        frame = self.frames[0]
        for f in self.frames[1:]:
            frame = frame.unionByName(f)
        packed = blocks.Packed(frame, self.n, self.d, self.n_blocks, self.bucket, 1, new.dense)
        warm = self.result.model if self.result else None
        if warm is not None:  # w = A alpha / (lam n): the same alphas, a larger n
            warm = Model(warm.w * ((self.n - n) / self.n), warm.alpha, warm.meta)
        self.result = fit(packed, replace(self.spec, max_epochs=self.epochs), warm, "incremental")
