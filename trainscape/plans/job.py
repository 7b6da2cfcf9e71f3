"""Jobs: what to train, when to stop, what a run returns; and the guards that refuse a job."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from trainscape.functions.losses import LogisticLoss


class JobRefused(ValueError):
    """A job that cannot run as it is."""


class NonConvexModelError(JobRefused):
    """ADMM asked for on a model without a convex objective."""


class OutOfWorkerMemory(JobRefused):
    """A model and batch that do not fit a worker."""


class ItemTooLarge(JobRefused):
    """A statistic above the item limit of a key-value channel."""


class IterationTooLong(JobRefused):
    """One iteration outlasts a worker's lifetime."""

    def __init__(self, message: str, suggested_batch: int):
        super().__init__(message)
        self.suggested_batch = suggested_batch


class TooLargeToCollect(JobRefused):
    """More numbers than the driver may hold."""


@dataclass(frozen=True)
class LrSchedule:
    """A step size that is constant or falls with the root of the epoch, counted from 1."""

    rate: float
    decay: bool = False

    @classmethod
    def constant(cls, rate: float) -> LrSchedule:
        return cls(rate)

    @classmethod
    def inv_sqrt(cls, rate: float) -> LrSchedule:
        return cls(rate, True)

    def at(self, epoch: int) -> float:
        return self.rate / np.sqrt(epoch) if self.decay else self.rate


@dataclass(frozen=True)
class StopRule:
    """Stop at a loss, after so many rounds, or when the model moves less than min_delta."""

    threshold: float | None = None
    max_rounds: int = 10
    min_delta: float = 0.0

    def reason(self, done: int, loss: float | None, moved: float) -> str | None:
        if loss is not None and not np.isfinite(loss):
            return "diverged"
        if self.threshold is not None and loss is not None and loss <= self.threshold:
            return "threshold"
        if self.min_delta and moved < self.min_delta:
            return "unchanged"
        return "rounds" if done >= self.max_rounds else None


@dataclass(frozen=True)
class JobSpec:
    algorithm: str = "ma"
    loss: object = field(default_factory=LogisticLoss)
    lr: LrSchedule = field(default_factory=lambda: LrSchedule(0.05))
    workers: int = 10
    batches: int = 10
    sync_every: int | None = None
    weighted: bool = True
    rho: float = 0.1
    inner_epochs: int = 10
    inner_tol: float = 0.0
    l1: float = 0.0
    pattern: str = "scatter_reduce"
    stop: StopRule = field(default_factory=StopRule)
    run_id: str = "run"
    reshuffle: bool = False

    def validate(self) -> JobSpec:
        if self.algorithm not in ("ga", "ma", "admm"):
            raise JobRefused(f"no algorithm {self.algorithm}")
        if self.algorithm == "admm" and not getattr(self.loss, "convex", False):
            raise NonConvexModelError("ADMM needs a convex objective")
        return self


TRACE = "run_id string, round int, epoch int, batch int, worker int, phase string, rows long, n_msgs long, n_bytes long"


@dataclass
class TrainResult:
    """The model with its intercept last, the validation loss of each round, why it stopped, and the trace rows."""

    w: np.ndarray
    history: list[dict]
    status: str
    trace_rows: list[tuple]

    def trace(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.trace_rows, TRACE)

    def metrics(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(h["round"], h["loss"], h["moved"]) for h in self.history], "round int, loss double, moved double")


#: Bytes of worker memory that a parameter and an activation take during training, and the runtime's own.
PARAMETER_COPIES, RUNTIME_BYTES = 4, 350_000_000


def footprint(model_bytes: int, batch: int, activation_bytes: int) -> int:
    return RUNTIME_BYTES + PARAMETER_COPIES * model_bytes + batch * activation_bytes


def check_memory(model_bytes: int, batch: int, activation_bytes: int, limit_gb: float = 3.0) -> int:
    """The bytes a worker needs for a model (weights, gradient, two moments) and a batch; refuses what does not fit."""
    need = footprint(model_bytes, batch, activation_bytes)
    if need > limit_gb * 1e9:
        raise OutOfWorkerMemory(f"{need / 1e9:.2f} GB of {limit_gb:g}; a batch of {max(0, int((limit_gb * 1e9 - footprint(model_bytes, 0, 0)) // activation_bytes))} fits")
    return need
