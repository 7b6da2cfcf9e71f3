"""Epochs to a threshold from a sample, and the run time that follows."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame

from trainscape.operators.linear import train
from trainscape.operators.partition import sample_hash
from trainscape.plans import analytic as A
from trainscape.plans.job import JobSpec, TrainResult


def estimate_epochs(examples: DataFrame, feats: list[str], keys: list[str], job: JobSpec, fraction: float = 0.1) -> tuple[int | None, TrainResult]:
    """Rounds until the sample's validation loss reaches the job's threshold, or None, and the run on the sample.

    The sample is fixed by hash; batches keep their number, so they shrink with it.
    """
    return sample_epochs(sample_hash(examples, keys, fraction), feats, keys, job)


def sample_epochs(sample: DataFrame, feats: list[str], keys: list[str], job: JobSpec) -> tuple[int | None, TrainResult]:
    """The same on a sample drawn before, which may be packed."""
    result = train(sample, feats, keys, job)
    return (result.history[-1]["round"] if result.status == "threshold" else None), result


def predict_runtime(spark, epochs: int, w: int, s_mb: float, m_mb: float, compute_s: float, infra: str = "fs", **options) -> DataFrame:
    """The analytic run time for an estimated number of epochs and a measured epoch."""
    params = A.parameter_grid(spark, [("estimate", "any", s_mb, m_mb, float(epochs), compute_s, 0.0)], [w])
    return {"fs": A.runtime_fs, "vc": A.runtime_vc, "hp": A.runtime_hp}[infra](params, **options)


def validate_epochs(examples: DataFrame, feats: list[str], keys: list[str], job: JobSpec, fraction: float = 0.1) -> dict:
    """Estimated and actual rounds of one job."""
    estimated, _ = estimate_epochs(examples, feats, keys, job, fraction)
    actual = train(examples, feats, keys, replace(job, run_id=f"{job.run_id}-full"))
    reached = actual.history[-1]["round"] if actual.status == "threshold" else None
    return {"estimated": estimated, "actual": reached}
