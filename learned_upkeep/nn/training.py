"""Training: the combined objective, Adam, and trainers for one driver or for all partitions.

A component is a class with ``initial(rng)`` parameters, ``loss(params, data)`` (a tensor: the mean
loss of the rows), ``row_loss(params, data)`` (an array), and ``imitation(params, teacher, data, …)``.
``data`` is a matrix of encoded rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from typing import Protocol

import numpy as np
from pyspark.sql import DataFrame

from .tensor import Tensor

Params = dict[str, np.ndarray]
#: What a value outside its domain adds to a row's loss: that of probability 1e-12.
UNSEEN_LOSS = 27.631021115928547
#: Most rows of weights or gradients that the driver gathers in a round.
GATHERED = 64


class Component(Protocol):
    name: str

    def initial(self, rng: np.random.Generator) -> Params: ...
    def loss(self, params: dict[str, Tensor], data: np.ndarray, noise: np.ndarray | None = None) -> Tensor: ...
    def row_loss(self, params: Params, data: np.ndarray) -> np.ndarray: ...
    def imitation(self, params: dict[str, Tensor], teacher: Params, data: np.ndarray, noise: np.ndarray | None = None) -> Tensor: ...
    def noise(self, rng: np.random.Generator, n: int) -> np.ndarray | None: ...


@dataclass(frozen=True)
class Settings:
    epochs: int = 20
    rate: float = 1e-3
    batch: int = 512
    seed: int = 1
    patience: int = 5


class Adam:
    def __init__(self, params: Params, rate: float) -> None:
        self.rate, self.t = rate, 0
        self.m, self.v = ({k: np.zeros_like(p) for k, p in params.items()} for _ in range(2))

    def step(self, params: Params, grads: Params) -> None:
        self.t += 1
        for k, g in grads.items():
            self.m[k] = 0.9 * self.m[k] + 0.1 * g
            self.v[k] = 0.999 * self.v[k] + 0.001 * g * g
            params[k] = params[k] - self.rate * (self.m[k] / (1 - 0.9**self.t)) / (np.sqrt(self.v[k] / (1 - 0.999**self.t)) + 1e-8)


def gradient(objective, params: Params) -> tuple[float, Params]:
    leaves = {k: Tensor(v) for k, v in params.items()}
    value = objective(leaves)
    value.backward()
    return float(value.value), {k: np.zeros_like(v) if leaves[k].grad is None else leaves[k].grad for k, v in params.items()}


@dataclass(frozen=True)
class Update:
    """Terms of an update.  Without a teacher or transfer rows it is plain training on ``new``."""

    new: np.ndarray
    transfer: np.ndarray | None = None
    teacher: Params | None = None
    lam: float = 0.0
    w_new: float = 1.0

    def objective(self, component: Component, at_new: np.ndarray, at_old: np.ndarray | None, rng: np.random.Generator):
        new = self.new[at_new]
        old = None if at_old is None else self.transfer[at_old]
        e_new, e_old = component.noise(rng, len(new)), None if old is None else component.noise(rng, len(old))

        def value(leaves: dict[str, Tensor]) -> Tensor:
            total = Tensor(0.0)
            if self.w_new and len(new):
                total = total + component.loss(leaves, new, e_new) * self.w_new
            if old is not None and len(old) and self.w_new < 1:
                w = 1 - self.w_new
                if self.lam:
                    total = total + component.imitation(leaves, self.teacher, old, e_old) * (w * self.lam)
                if self.lam < 1:
                    total = total + component.loss(leaves, old, e_old) * (w * (1 - self.lam))
            return total

        return value


def fit(component: Component, update: Update, start: Params | None = None, settings: Settings = Settings()) -> tuple[Params, list[float]]:  # noqa: B008
    """Mini-batches on the driver, for rows that are bounded by sampling; returns parameters and the loss of each epoch.

    Batches of new and transfer rows run side by side; the shorter of the two is repeated.
    """
    rng = np.random.default_rng(settings.seed)
    params = {k: v.copy() for k, v in (start or component.initial(rng)).items()}
    adam = Adam(params, settings.rate)
    n_old = 0 if update.transfer is None else len(update.transfer)
    steps = max(1, -(-max(len(update.new), n_old) // settings.batch))
    history, best, waited = [], np.inf, 0
    for _ in range(settings.epochs):
        take = lambda n: np.empty(0, int) if not n else np.resize(rng.permutation(n), max(n, min(steps * settings.batch, max(len(update.new), n_old))))
        news = np.array_split(take(len(update.new)), steps)
        olds = np.array_split(take(n_old), steps) if n_old else [None] * steps
        total = 0.0
        for a, b in zip(news, olds, strict=True):
            value, grads = gradient(update.objective(component, a, b, rng), params)
            adam.step(params, grads)
            total += value
        history.append(total / steps)
        if history[-1] < best - 1e-4 * abs(best if np.isfinite(best) else 1):
            best, waited = history[-1], 0
        else:
            waited += 1
            if waited >= settings.patience:
                break
    return params, history


def matrix(df: DataFrame, columns: list[str], cap: int = 2_000_000) -> np.ndarray:
    """A bounded sample as a matrix.  More than ``cap`` rows are refused: sample first."""
    table = df.select(*columns).limit(cap + 1).toArrow()
    if table.num_rows > cap:
        raise ValueError(f"more than {cap} rows; take a hash sample, or train by partitions")
    return np.column_stack([table.column(c).to_numpy().astype("float64") for c in columns]) if table.num_rows else np.empty((0, len(columns)))


def _rows(pdf, columns: list[str]) -> np.ndarray:
    return pdf[columns].to_numpy("float64")


def _flat(params: Params) -> np.ndarray:
    return np.concatenate([params[k].ravel() for k in sorted(params)])


def _shaped(flat: np.ndarray, like: Params) -> Params:
    out, at = {}, 0
    for k in sorted(like):
        out[k] = flat[at : at + like[k].size].reshape(like[k].shape)
        at += like[k].size
    return out


def _summed(parts: DataFrame, size: int) -> tuple[float, np.ndarray, int]:
    """Sums of loss and vector over rows (n, loss, vector), one for each task, all of which run at once.

    At most ``GATHERED`` rows reach the driver; of more tasks, tasks add up vectors first.
    """
    import pandas as pd

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total, vector, n = 0.0, np.zeros(size), 0
        for pdf in frames:
            for row in pdf.itertuples(index=False):
                total, vector, n = total + row.loss, vector + row.vector, n + row.n
        if n:
            yield pd.DataFrame({"n": [n], "loss": [total], "vector": [vector.tolist()]})

    if parts.rdd.getNumPartitions() > GATHERED:
        parts = parts.repartition(GATHERED).mapInPandas(run, parts.schema)
    total, vector, n = 0.0, np.zeros(size), 0
    for row in parts.collect():
        total, vector, n = total + row["loss"], vector + np.asarray(row["vector"]), n + row["n"]
    return total, vector, n


def full_gradient(df: DataFrame, component: Component, params: Params, columns: list[str]) -> tuple[float, Params, int]:
    """Exact mean loss and gradient over all rows: one small row from each partition."""
    import pandas as pd

    shared = df.sparkSession.sparkContext.broadcast(params)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total, grad, n = 0.0, None, 0
        for pdf in batches:
            rows = _rows(pdf, columns)
            if len(rows):
                value, g = gradient(lambda leaves, rows=rows: component.loss(leaves, rows, component.noise(np.random.default_rng(0), len(rows))), shared.value)
                flat = _flat(g) * len(rows)
                total, grad, n = total + value * len(rows), flat if grad is None else grad + flat, n + len(rows)
        if n:
            yield pd.DataFrame({"n": [n], "loss": [total], "vector": [grad.tolist()]})

    total, grad, n = _summed(df.select(*columns).mapInPandas(run, "n long, loss double, vector array<double>"), _flat(params).size)
    return total / max(1, n), _shaped(grad / max(1, n), params), n


def _blocks(batches: Iterator, rows: int = 200_000) -> Iterator:
    """Arrow batches joined to about so many rows, so that an optimizer has a run to settle in and memory stays bounded."""
    import pandas as pd

    held, n = [], 0
    for pdf in batches:
        held.append(pdf)
        n += len(pdf)
        if n >= rows:
            yield pd.concat(held)
            held, n = [], 0
    if held:
        yield pd.concat(held)


@dataclass(frozen=True)
class Teaching:
    """What an update has besides its rows: the teacher, lambda and the weight of the new rows.  Rows then carry ``is_new``."""

    teacher: Params
    lam: float
    w_new: float


def fit_by_partitions(df: DataFrame, component: Component, columns: list[str], start: Params, rounds: int = 5, settings: Settings = Settings(epochs=1), teaching: Teaching | None = None) -> Params:  # noqa: B008
    """Rounds of local training on every partition from shared weights, averaged by rows: for data of any size.

    The rate falls along a half cosine over the rounds.  With ``teaching`` it is the combined update, and ``df`` holds the batch (``is_new``) and the
    transfer set, which should be mixed over the partitions.
    """
    import pandas as pd

    params = start
    for r in range(rounds):
        shared = df.sparkSession.sparkContext.broadcast(params)

        def run(batches: Iterator[pd.DataFrame], shared=shared, r=r) -> Iterator[pd.DataFrame]:
            own, n = shared.value, 0
            rate = settings.rate * (1 + np.cos(np.pi * r / rounds)) / 2
            for pdf in _blocks(batches):
                rows = _rows(pdf, columns)
                if len(rows):
                    new = pdf["is_new"].to_numpy(bool) if teaching else None
                    update = Update(rows[new], rows[~new], teaching.teacher, teaching.lam, teaching.w_new) if teaching else Update(rows)
                    own, _ = fit(component, update, own, Settings(settings.epochs, rate, settings.batch, settings.seed + r))
                    n += len(rows)
            if n:
                yield pd.DataFrame({"n": [n], "loss": [0.0], "vector": [(_flat(own) * n).tolist()]})

        rows = df.select(*columns, *["is_new"] * (teaching is not None))
        _, total, n = _summed(rows.mapInPandas(run, "n long, loss double, vector array<double>"), _flat(params).size)
        if n:
            params = _shaped(total / n, params)
        shared.unpersist()
    return params


#: Most steps of :func:`fit_counted` in an epoch; fewer rows take as many as they make mini-batches.
STEPS_AN_EPOCH = 64


def fit_counted(component: Component, cells: np.ndarray, new: np.ndarray, start: Params, settings: Settings, old: np.ndarray | None = None, teaching: Teaching | None = None) -> tuple[Params, int]:
    """Training on all rows from the counts of their distinct values; returns parameters and the rows that gradients were taken of.

    ``new`` and ``old`` (the transfer set) count the rows of each of ``cells``.  A loss depends on a
    row's values only, so the weighted sum over cells is the mean over all rows, and each step takes
    its exact gradient: the cost follows the cells, however many rows there are.  The rate falls
    along a half cosine.  The component has ``counted``, the objective of weighted rows.
    """
    share = lambda n: n / n.sum() if n is not None and n.sum() else np.zeros(len(cells))
    likely, like = share(new), np.zeros(len(cells))
    if teaching:
        kept = (1 - teaching.w_new) * share(old)
        likely, like = teaching.w_new * likely + (1 - teaching.lam) * kept, teaching.lam * kept
    met = likely + like > 0
    if not met.any():
        return start, 0
    objective = component.counted(np.nan_to_num(cells[met]), likely[met], like[met], teaching.teacher if teaching else None)
    batches = -int(-max(new.sum(), 0 if old is None else old.sum()) // settings.batch)
    params, adam, steps = dict(start), Adam(start, settings.rate), settings.epochs * max(1, min(STEPS_AN_EPOCH, batches))
    for t in range(steps):
        adam.rate = settings.rate * (1 + np.cos(np.pi * t / steps)) / 2
        adam.step(params, gradient(objective, params)[1])
    return params, steps * int(met.sum())


def losses(component: Component, params: Params, data: np.ndarray) -> np.ndarray:
    """The loss of each row.  A code outside its domain, or a missing one, adds ``UNSEEN_LOSS`` and is otherwise read as the nearest."""
    sizes = np.array(getattr(component, "sizes", None) or (component.categories,))
    codes = data[:, : sizes.size]
    with np.errstate(invalid="ignore"):
        unseen = ~((codes >= 0) & (codes < sizes))
    if not unseen.any() and not np.isnan(data).any():
        return component.row_loss(params, data)
    missing = np.isnan(data[:, sizes.size :]).any(axis=1) & ~unseen.any(axis=1)
    return component.row_loss(params, np.nan_to_num(data)) + UNSEEN_LOSS * (unseen.sum(axis=1) + missing)


def score(df: DataFrame, component: Component, params: Params, columns: list[str]) -> DataFrame:
    """``df`` with a column ``loss``: weights are broadcast, rows stream through in Arrow batches, nothing is shuffled."""
    import pyarrow as pa

    shared = df.sparkSession.sparkContext.broadcast(params)
    names = df.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                data = np.column_stack([b.column(c).to_numpy(zero_copy_only=False).astype("float64") for c in columns])
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(losses(component, shared.value, data))], [*names, "loss"])

    return df.mapInArrow(run, df.schema.simpleString()[7:-1] + ",loss:double")
