"""A training pipeline: scale and store the features, search the rates, measure and price the best model."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from trainscape.functions.losses import LogisticLoss
from trainscape.operators.features import minmax_apply, minmax_fit, plant_label
from trainscape.operators.linear import best_rate, predict, tune_lr
from trainscape.operators.metrics import class_metrics
from trainscape.operators.partition import assign_batches, assign_workers, split
from trainscape.plans.constants import PRICE_FS, PRICE_VC
from trainscape.plans.tasks import DENSE, KEYS, dense28_raw

RATES = [round(0.01 * i, 2) for i in range(1, 11)]


def preprocess(spark: SparkSession, sf_dir: str, path: str | None = None, workers: int = 10, batches: int = 10) -> DataFrame:
    """Scaled examples with labels, split, worker and batch; stored by worker and read again if a path is given."""
    raw = dense28_raw(spark, sf_dir)
    df = plant_label(minmax_apply(raw, minmax_fit(raw, DENSE), DENSE), DENSE, KEYS)
    df = assign_batches(assign_workers(split(df, KEYS), KEYS, workers), KEYS, batches)
    if path is None:
        return df
    df.write.mode("overwrite").partitionBy("worker").parquet(path)
    return spark.read.parquet(path)


def run_pipeline(examples: DataFrame, rates: list[float] = RATES, epochs: int = 10, batches: int = 10, loss=None) -> tuple[DataFrame, DataFrame]:
    """((lr, loss, w) of each rate, measures of the best model on the validation rows)."""
    tuned = tune_lr(examples, DENSE, loss or LogisticLoss(), rates, epochs, batches).persist()
    lr = best_rate(tuned)
    best = tuned.where(f"lr = {lr!r}D").first()["w"]
    return tuned, class_metrics(predict(examples.where("split = 'validation'"), best, DENSE, KEYS))


def price_pipeline(seconds: float, jobs: int = 10, workers: int = 10, infra: str = "fs") -> float:
    """Dollars of parallel jobs that run side by side; simulated."""
    return seconds * jobs * workers * (PRICE_FS if infra == "fs" else PRICE_VC)
