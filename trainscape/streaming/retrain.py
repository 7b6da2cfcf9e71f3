"""Continuous retraining and arrivals over event streams."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trainscape.functions.losses import LogisticLoss
from trainscape.operators.linear import gradient
from trainscape.sources.tables import exists, load_checkpoint, save_checkpoint

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """A file stream of events with ts as a timestamp, fit for watermarks."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def event_features(events: DataFrame) -> DataFrame:
    """(event_id, y, f0..f2): clicks against the rest, from value, hour and the k of props."""
    k = F.from_json("props", "k INT")["k"]
    return events.select("event_id", F.when(F.col("event_type") == "click", 1.0).otherwise(-1.0).alias("y"), (F.least(F.col("value"), F.lit(500.0)) / 250.0 - 1).alias("f0"), (F.hour("ts") / 11.5 - 1).alias("f1"), (k / 49.5 - 1).alias("f2"))


class Retrainer:
    """A model that takes a step for every micro-batch; a batch that is delivered again is not applied twice.

    With a folder the model is saved by batch id after each batch, and a new
    Retrainer with that folder goes on from the last one.
    """

    def __init__(self, feats: list[str] = ("f0", "f1", "f2"), lr: float = 0.1, steps: int = 1, loss=None, spark: SparkSession | None = None, folder: str | None = None):
        self.feats, self.lr, self.steps, self.loss = list(feats), lr, steps, loss or LogisticLoss()
        self.w, self.seen, self.history, self.folder = np.zeros(len(self.feats) + 1), -1, [], folder
        last = load_checkpoint(spark, folder, "retrain") if spark and folder and exists(spark, folder) else []
        if last:
            self.w, self.seen = np.array(last[0]["w"]), last[0]["iteration"]

    def apply(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id <= self.seen:
            return
        rows = event_features(batch).persist()
        n = 0
        for _ in range(self.steps):
            g, n = gradient(rows, self.w, self.feats, self.loss)
            self.w = self.w - self.lr * g
        rows.unpersist()
        self.seen = batch_id
        if self.folder:
            save_checkpoint(batch.sparkSession, self.folder, "retrain", [(-1, 0, batch_id, [float(v) for v in self.w], [])])
        self.history.append((batch_id, n, [float(v) for v in self.w]))

    def run(self, stream: DataFrame, checkpoint: str) -> list[tuple]:
        """Drains the stream and returns (batch, rows, model) of each micro-batch."""
        query = stream.writeStream.foreachBatch(self.apply).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
        query.awaitTermination()
        return self.history


def sessions(events: DataFrame, gap: str = "30 minutes", watermark: str | None = None) -> DataFrame:
    """(user_id, start, end, n, value) of each user's sessions; late events beyond the watermark are left out of streams."""
    e = events.withColumn("ts", F.col("ts").cast("timestamp"))
    if watermark:
        e = e.withWatermark("ts", watermark)
    s = e.groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.count("*").alias("n"), F.sum("value").alias("value"))
    return s.select("user_id", F.col("s.start").alias("start"), F.col("s.end").alias("end"), "n", "value")


def arrivals(events: DataFrame, every: str = "1 hour", watermark: str | None = None) -> DataFrame:
    """(start, event_type, n) of tumbling windows."""
    e = events.withColumn("ts", F.col("ts").cast("timestamp"))
    if watermark:
        e = e.withWatermark("ts", watermark)
    return e.groupBy(F.window("ts", every).alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def unique_events(stream: DataFrame, watermark: str = "10 minutes") -> DataFrame:
    return stream.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def completions(requests: DataFrame, results: DataFrame, within: str = "1 hour") -> DataFrame:
    """(request, user_id, asked, done): requests (event_id, user_id, ts) joined with the same user's results that come within an interval; both sides carry watermarks."""
    r = requests.select(F.col("event_id").alias("request"), "user_id", F.col("ts").alias("asked")).withWatermark("asked", within)
    d = results.select(F.col("user_id").alias("_user"), F.col("ts").alias("done")).withWatermark("done", within)
    on = (F.col("user_id") == F.col("_user")) & (F.col("done") >= F.col("asked")) & (F.col("done") <= F.col("asked") + F.expr(f"interval {within}"))
    return r.join(d, on).select("request", "user_id", "asked", "done")


def user_models(stream: DataFrame, lr: float = 0.1) -> DataFrame:
    """(user_id, n, w) after each micro-batch: a logistic model per user, kept in state and moved by the user's new events."""
    import pandas as pd

    loss = LogisticLoss()

    def update(key, frames, state):
        n, w = state.get if state.exists else (0, [0.0] * 4)
        w = np.array(w)
        for f in frames:
            f = f.sort_values("event_id")
            x, y = np.column_stack([f["f0"], f["f1"], f["f2"], np.ones(len(f))]), f["y"].to_numpy()
            for row, label in zip(x, y):
                w = w - lr * loss.np_slope(label * (row @ w)) * label * row
            n += len(f)
        state.update((n, [float(v) for v in w]))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "w": [[float(v) for v in w]]})

    made = stream.select("user_id", "event_id", F.when(F.col("event_type") == "click", 1.0).otherwise(-1.0).alias("y"), (F.least(F.col("value"), F.lit(500.0)) / 250.0 - 1).alias("f0"), (F.hour("ts") / 11.5 - 1).alias("f1"), (F.from_json("props", "k INT")["k"] / 49.5 - 1).alias("f2"))
    return made.groupBy("user_id").applyInPandasWithState(update, "user_id long, n long, w array<double>", "n long, w array<double>", "update", "NoTimeout")
