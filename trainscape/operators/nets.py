"""Small neural networks in numpy, trained by gradient or model averaging inside Arrow kernels."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trainscape.functions.vectors import sum_vectors
from trainscape.operators.partition import assign_batches


def _softmax_loss(logits: np.ndarray, y: np.ndarray) -> tuple[float, np.ndarray]:
    z = logits - logits.max(1, keepdims=True)
    p = np.exp(z)
    p /= p.sum(1, keepdims=True)
    rows = np.arange(len(y))
    loss = float(-np.log(np.maximum(p[rows, y], 1e-300)).sum())
    p[rows, y] -= 1
    return loss, p


class _Net:
    """Parameters are one flat vector; loss_grad returns the summed loss and gradient of a block."""

    convex = False
    shapes: list[tuple[int, ...]]

    @property
    def size(self) -> int:
        return int(sum(np.prod(s) for s in self.shapes))

    @property
    def model_bytes(self) -> int:
        return 8 * self.size

    def init(self, seed: int = 0) -> np.ndarray:
        r = np.random.default_rng(seed)
        return np.concatenate([(r.normal(size=s) * np.sqrt(2.0 / max(1, np.prod(s[:-1])))).ravel() if len(s) > 1 else np.zeros(s) for s in self.shapes])

    def split(self, w: np.ndarray) -> list[np.ndarray]:
        out, at = [], 0
        for s in self.shapes:
            n = int(np.prod(s))
            out.append(w[at : at + n].reshape(s))
            at += n
        return out

    def logits(self, w: np.ndarray, x: np.ndarray) -> np.ndarray:
        return self.forward(self.split(w), x)[0]

    def loss_grad(self, w: np.ndarray, x: np.ndarray, y: np.ndarray) -> tuple[float, np.ndarray]:
        parts = self.split(w)
        logits, back = self.forward(parts, x)
        loss, d = _softmax_loss(logits, y)
        return loss, np.concatenate([g.ravel() for g in back(d)])


@dataclass
class Mlp(_Net):
    """One hidden layer; hidden 0 is softmax regression."""

    dims: int = 64
    hidden: int = 32
    classes: int = 10

    def __post_init__(self):
        self.convex = self.hidden == 0
        self.shapes = [(self.dims, self.hidden), (self.hidden,), (self.hidden, self.classes), (self.classes,)] if self.hidden else [(self.dims, self.classes), (self.classes,)]

    def forward(self, p, x):
        if not self.hidden:
            return x @ p[0] + p[1], lambda d: [x.T @ d, d.sum(0)]
        h = x @ p[0] + p[1]
        a = np.maximum(h, 0)

        def back(d):
            dh = (d @ p[2].T) * (h > 0)
            return [x.T @ dh, dh.sum(0), a.T @ d, d.sum(0)]

        return a @ p[2] + p[3], back


def _shift(x: np.ndarray, dy: int, dx: int) -> np.ndarray:
    """x[n, h, w, c] moved by (dy, dx), zeros from outside."""
    out = np.zeros_like(x)
    h, w = x.shape[1:3]
    ys, xs = slice(max(dy, 0), h + min(dy, 0)), slice(max(dx, 0), w + min(dx, 0))
    yt, xt = slice(max(-dy, 0), h + min(-dy, 0)), slice(max(-dx, 0), w + min(-dx, 0))
    out[:, yt, xt] = x[:, ys, xs]
    return out


_OFFSETS = [(dy, dx) for dy in (-1, 0, 1) for dx in (-1, 0, 1)]


def _depthwise(k, x):
    """A 3 x 3 filter per channel; k[9, c]."""
    return sum(_shift(x, *o) * k[i] for i, o in enumerate(_OFFSETS))


def _depthwise_back(k, x, d):
    return np.stack([(_shift(x, *o) * d).sum((0, 1, 2)) for o in _OFFSETS]), sum(_shift(d * k[i], -o[0], -o[1]) for i, o in enumerate(_OFFSETS))


@dataclass
class SeparableConvNet(_Net):
    """Blocks of a depthwise 3 x 3 and a pointwise filter with rectifiers, then an average and a linear layer."""

    side: int = 8
    channels: int = 1
    width: int = 8
    blocks: int = 2
    classes: int = 10

    def __post_init__(self):
        self.shapes = []
        c = self.channels
        for _ in range(self.blocks):
            self.shapes += [(9, c), (c, self.width), (self.width,)]
            c = self.width
        self.shapes += [(c * self.side * self.side, self.classes), (self.classes,)]

    def forward(self, p, x):
        a, tape = x.reshape(-1, self.side, self.side, self.channels), []
        for b in range(self.blocks):
            k, m, bias = p[3 * b : 3 * b + 3]
            u = _depthwise(k, a)
            z = u @ m + bias
            tape.append((a, u, z))
            a = np.maximum(z, 0)
        flat = a.reshape(len(a), -1)

        def back(d):
            grads = [flat.T @ d, d.sum(0)]
            da = (d @ p[-2].T).reshape(a.shape)
            for b in reversed(range(self.blocks)):
                before, u, z = tape[b]
                k, m, _ = p[3 * b : 3 * b + 3]
                dz = da * (z > 0)
                gm = np.tensordot(u, dz, ((0, 1, 2), (0, 1, 2)))
                gk, da = _depthwise_back(k, before, dz @ m.T)
                grads = [gk, gm, dz.sum((0, 1, 2)), *grads]
            return grads

        return flat @ p[-2] + p[-1], back


@dataclass
class ResidualNet(_Net):
    """A pointwise lift, then blocks of depthwise and pointwise filters around identity shortcuts, then a linear layer."""

    side: int = 8
    channels: int = 1
    width: int = 8
    blocks: int = 2
    classes: int = 10

    def __post_init__(self):
        self.shapes = [(self.channels, self.width), (self.width,)]
        for _ in range(self.blocks):
            self.shapes += [(9, self.width), (self.width, self.width), (self.width,)]
        self.shapes += [(self.width * self.side * self.side, self.classes), (self.classes,)]

    def forward(self, p, x):
        image = x.reshape(-1, self.side, self.side, self.channels)
        a, tape = image @ p[0] + p[1], []
        for b in range(self.blocks):
            k, m, bias = p[2 + 3 * b : 5 + 3 * b]
            u = _depthwise(k, np.maximum(a, 0))
            tape.append((a, u))
            a = a + u @ m + bias
        flat = a.reshape(len(a), -1)

        def back(d):
            grads = [flat.T @ d, d.sum(0)]
            da = (d @ p[-2].T).reshape(a.shape)
            for b in reversed(range(self.blocks)):
                before, u = tape[b]
                k, m, _ = p[2 + 3 * b : 5 + 3 * b]
                gm = np.tensordot(u, da, ((0, 1, 2), (0, 1, 2)))
                gk, dr = _depthwise_back(k, np.maximum(before, 0), da @ m.T)
                grads = [gk, gm, da.sum((0, 1, 2)), *grads]
                da = da + dr * (before > 0)
            return [np.tensordot(image, da, ((0, 1, 2), (0, 1, 2))), da.sum((0, 1, 2)), *grads]

        return flat @ p[-2] + p[-1], back


def _block(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    x = batch.column("x")
    return x.flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1).astype(float), batch.column("y").to_numpy(zero_copy_only=False).astype(int)


def net_gradient(rows: DataFrame, net: _Net, w: np.ndarray) -> tuple[np.ndarray, float, int]:
    """(mean gradient, mean loss, rows) over rows (x, y): one vector per task, summed by coordinate."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, loss, n = np.zeros(net.size), 0.0, 0
        for batch in batches:
            if batch.num_rows:
                x, y = _block(batch)
                l, g = net.loss_grad(w, x, y)
                total, loss, n = total + g, loss + l, n + len(y)
        if n:
            yield pa.RecordBatch.from_arrays([pa.array([n]), pa.array([loss]), pa.array([total], pa.list_(pa.float64()))], ["n", "loss", "g"])

    parts = rows.select("x", "y").mapInArrow(run, "n long, loss double, g array<double>").select("n", "loss", "g").persist()
    sums = {r["coord"]: r["value"] for r in sum_vectors(parts, [], "g").collect()}
    totals = parts.agg(F.sum("n").alias("n"), F.sum("loss").alias("loss")).first()
    parts.unpersist()
    n = totals["n"] or 0
    return np.array([sums.get(i, 0.0) for i in range(net.size)]) / max(n, 1), (totals["loss"] or 0.0) / max(n, 1), n


def net_ga(rows: DataFrame, net: _Net, lr: float, steps: int, batches: int = 1, w: np.ndarray | None = None) -> tuple[np.ndarray, list[float]]:
    """Gradient averaging: step s takes the rows with batch = s mod batches; returns the model and the loss before each step."""
    w, losses = net.init() if w is None else w, []
    for s in range(steps):
        g, loss, _ = net_gradient(rows if batches == 1 else rows.where(F.col("batch") == s % batches), net, w)
        losses.append(loss)
        w = w - lr * g
    return w, losses


def net_ma(rows: DataFrame, net: _Net, lr: float, rounds: int, workers: int, batches: int = 4, w: np.ndarray | None = None) -> tuple[np.ndarray, list[float]]:
    """Model averaging: each worker's own pass over its hashed batches, then the row-weighted mean; the loss is that seen during the pass.

    A batch's gradient is summed over all Arrow batches that hold its rows, so steps do not depend on how rows lie.
    """
    w, losses = net.init() if w is None else w, []
    laid = assign_batches(rows.select("worker", "vec_id", "x", "y"), ["vec_id"], batches).repartition(workers, "worker").sortWithinPartitions("worker", "batch", "vec_id").persist()
    for _ in range(rounds):
        start = w

        def run(parts: Iterator[pa.RecordBatch], start=start) -> Iterator[pa.RecordBatch]:
            state: dict[int, list] = {}
            current, total, count = None, None, 0

            def close() -> None:
                if count:
                    state[current[0]][0] = state[current[0]][0] - lr * total / count

            for part in parts:
                if not part.num_rows:
                    continue
                x, y = _block(part)
                worker, batch = (part.column(c).to_numpy(zero_copy_only=False) for c in ("worker", "batch"))
                cuts = np.flatnonzero((worker[1:] != worker[:-1]) | (batch[1:] != batch[:-1])) + 1
                for lo, hi in zip([0, *cuts], [*cuts, part.num_rows]):
                    key = (int(worker[lo]), int(batch[lo]))
                    if key != current:
                        close()
                        current, total, count = key, 0.0, 0
                    own = state.setdefault(key[0], [start.copy(), 0, 0.0])
                    l, g = net.loss_grad(own[0], x[lo:hi], y[lo:hi])
                    total, count = total + g, count + hi - lo
                    own[1], own[2] = own[1] + hi - lo, own[2] + l
            close()
            if state:
                yield pa.RecordBatch.from_arrays([pa.array([s[1] for s in state.values()]), pa.array([s[2] for s in state.values()]), pa.array([s[0] for s in state.values()], pa.list_(pa.float64()))], ["n", "loss", "w"])

        local = laid.mapInArrow(run, "n long, loss double, w array<double>").persist()
        n, loss = local.agg(F.sum("n"), F.sum("loss")).first()
        w = w.copy()
        for r in sum_vectors(local, [], "w", "n").collect():
            w[r["coord"]] = r["value"] / r["weight"]
        losses.append(loss / n)
        local.unpersist()
    laid.unpersist()
    return w, losses


def net_predict(rows: DataFrame, net: _Net, w: np.ndarray, keys: list[str]) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x, _ = _block(batch)
            hat = net.logits(w, x).argmax(1) if batch.num_rows else np.empty(0, int)
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in keys), batch.column("y"), pa.array(hat.astype(np.int32))], [*keys, "y", "label_hat"])

    schema = ", ".join([*(f"{k} {dict(rows.dtypes)[k]}" for k in keys), "y int, label_hat int"])
    return rows.select(*keys, "x", "y").mapInArrow(run, schema)
