"""Update policies for the networks: the same names and weights as on the count model."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from contextlib import contextmanager
from dataclasses import dataclass, replace

import numpy as np
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..nn.training import Component, Params, Settings, Teaching, Update, fit, fit_by_partitions, fit_counted
from .update import LAMBDA, LAMBDA_GRID, new_weight


@dataclass(frozen=True)
class Model:
    """One version of a learned component."""

    component: Component
    params: Params
    rows: int
    version: int = 0
    parent: int | None = None
    steps: int = 0  # rows times epochs spent on training this version: a cost that doesn't depend on the machine


#: Rows that a training task has at least: averaging over tasks of fewer rows leaves too few steps in a row.
ROWS_A_TASK = 50_000


@contextmanager
def _spread(df: DataFrame, rows: int) -> Iterator[DataFrame]:
    """The rows dealt to as many tasks as run at once and have enough of them, old and new mixed, and held for all rounds."""
    tasks = max(1, min(df.sparkSession.sparkContext.defaultParallelism, rows // ROWS_A_TASK))
    dealt = (df.repartition(tasks, "rk") if "rk" in df.columns else df.repartition(tasks)).persist(StorageLevel.MEMORY_AND_DISK)
    try:
        yield dealt
    finally:
        dealt.unpersist()


def train(component: Component, data: np.ndarray, rows: int, settings: Settings = Settings()) -> Model:  # noqa: B008
    params, history = fit(component, Update(data), None, settings)
    return Model(component, params, rows, steps=len(history) * len(data))


def train_all(component: Component, df: DataFrame, columns: list[str], settings: Settings = Settings()) -> Model:  # noqa: B008
    """Training on all rows by partitions, an averaging round for each epoch."""
    rows = df.count()
    with _spread(df, rows) as parts:
        params = fit_by_partitions(parts, component, columns, component.initial(np.random.default_rng(settings.seed)), settings.epochs, replace(settings, epochs=1))
    return Model(component, params, rows, steps=settings.epochs * rows)


def fine_tune(model: Model, batch: np.ndarray, n_new: int, settings: Settings = Settings(), rate: float | None = None) -> Model:  # noqa: B008
    """Training on the batch alone.  The rate without drift is the base rate times new over old rows."""
    rate = settings.rate * n_new / max(1, model.rows) if rate is None else rate
    params, history = fit(model.component, Update(batch), model.params, replace(settings, rate=rate))
    return Model(model.component, params, model.rows + n_new, model.version + 1, model.version, len(history) * len(batch))


def distil(model: Model, batch: np.ndarray, transfer: np.ndarray, n_new: int, lam: float = LAMBDA, alpha: str | float = "described", settings: Settings = Settings(), start: str = "copy") -> Model:  # noqa: B008
    """The combined update; ``start`` is ``copy`` of the teacher or ``fresh``."""
    u = Update(batch, transfer, model.params, lam, new_weight(n_new, model.rows, alpha))
    params, history = fit(model.component, u, model.params if start == "copy" else None, settings)
    return Model(model.component, params, model.rows + n_new, model.version + 1, model.version, len(history) * (len(batch) + 2 * len(transfer)))


def plain_distillation(teacher: Model, student: Component, transfer: np.ndarray, lam: float, settings: Settings = Settings()) -> Model:  # noqa: B008
    """Teacher imitation and ordinary loss on the transfer set, no batch: a smaller student only needs outputs of the same shape."""

    class Student:
        """The student's losses, with imitation of the teacher's outputs."""

        name = student.name
        initial, loss, row_loss, noise = student.initial, student.loss, student.row_loss, student.noise

        @staticmethod
        def imitation(params, teacher_params, data, noise=None):
            return cross_imitation(teacher.component, teacher_params, student, params, data)

    u = Update(transfer[:0], transfer, teacher.params, lam, 0.0)
    params, history = fit(Student, u, None, settings)
    return Model(student, params, teacher.rows, 0, None, len(history) * 2 * len(transfer))


def cross_imitation(teacher: Component, teacher_params: Params, student: Component, params, data: np.ndarray):
    """Imitation between an autoregressive teacher and student of different widths."""
    from ..nn.losses import soft_cross_entropy
    from ..nn.tensor import Tensor

    x = student.encode(data)
    t = teacher.logits({k: Tensor(v) for k, v in teacher_params.items()}, x).value
    z, out = student.logits(params, x), Tensor(0.0)
    for a, b in zip(student.starts, student.starts[1:], strict=False):
        out = out + soft_cross_entropy(t[:, a:b], z[:, a:b], student.temperature)
    return out * (1 / len(student.sizes))


def generations(model: Model, transfer: np.ndarray, n: int, lam: float = 1.0, settings: Settings = Settings()) -> Model:  # noqa: B008
    """Self-distillation several times over: each student is the next teacher."""
    for _ in range(n):
        params, history = fit(model.component, Update(transfer[:0], transfer, model.params, lam, 0.0), model.params, settings)
        model = Model(model.component, params, model.rows, model.version + 1, model.version, len(history) * 2 * len(transfer))
    return model


def anchored(model: Model, batch: np.ndarray, old: np.ndarray, n_new: int, strength: float = 100.0, settings: Settings = Settings()) -> Model:  # noqa: B008
    """Fine-tuning with a quadratic anchor to the old weights, weighted by squared gradients on old rows."""
    from ..nn.tensor import square
    from ..nn.training import gradient

    rng = np.random.default_rng(settings.seed)
    importance = {k: np.zeros_like(v) for k, v in model.params.items()}
    blocks = np.array_split(old[: 64 * 50], 50)
    for rows in blocks:
        if len(rows):
            _, g = gradient(lambda leaves, rows=rows: model.component.loss(leaves, rows, model.component.noise(rng, len(rows))), model.params)
            for k in g:
                importance[k] += g[k] ** 2 / len(blocks)
    base = model.component

    class Anchored:
        name, initial, row_loss, noise, imitation = base.name, base.initial, base.row_loss, base.noise, base.imitation

        @staticmethod
        def loss(params, data, noise=None):
            out = base.loss(params, data, noise)
            for k, w in importance.items():
                out = out + (square(params[k] - model.params[k]) * w).sum() * strength
            return out

    params, history = fit(Anchored, Update(batch), model.params, settings)
    return Model(base, params, model.rows + n_new, model.version + 1, model.version, len(history) * len(batch))


def policies(model: Model, old: np.ndarray, batch: np.ndarray, transfer: np.ndarray, n_new: int, settings: Settings = Settings(), lam: float = LAMBDA, alpha: str | float = "described", which: tuple[str, ...] | None = None) -> dict[str, Model]:  # noqa: B008
    rows = model.rows + n_new
    makers = {
        "stale": lambda: model,
        "retrain": lambda: replace(train(model.component, np.concatenate([old, batch]), rows, settings), rows=rows),
        "fine_tune": lambda: fine_tune(model, batch, n_new, settings, settings.rate),
        "kd": lambda: distil(model, batch, transfer, n_new, lam, alpha, settings),
        "pooled": lambda: replace(train(model.component, np.concatenate([transfer, batch]), rows, settings), rows=rows),
        "anchored": lambda: anchored(model, batch, old, n_new, settings=settings),
    }
    return {k: makers[k]() for k in which or [k for k in makers if k != "anchored"]}


def policies_all(model: Model, old: DataFrame, batch: DataFrame, transfer: DataFrame, columns: list[str], n_new: int, settings: Settings = Settings(), lam: float = LAMBDA, alpha: str | float = "described", which: tuple[str, ...] = ("stale", "retrain", "fine_tune", "kd", "pooled")) -> dict[str, Model]:  # noqa: B008
    """:func:`policies` on all rows where they lie: each epoch is a round over the partitions.  Only weights reach the driver."""
    rows, c = model.rows + n_new, model.component
    tagged = lambda df, new: df.select("rk", *columns, F.lit(new).alias("is_new"))
    mixed = lambda df: tagged(df, False).unionByName(tagged(batch, True))
    one = replace(settings, epochs=1)
    version = {"version": model.version + 1, "parent": model.version}

    def tuned() -> Model:
        with _spread(batch.select("rk", *columns), n_new) as parts:
            params = fit_by_partitions(parts, c, columns, model.params, settings.epochs, one)
        return Model(c, params, rows, **version, steps=settings.epochs * n_new)

    def distilled() -> Model:
        n_both = n_new + transfer.count()
        with _spread(mixed(transfer), n_both) as both:
            params = fit_by_partitions(both, c, columns, model.params, settings.epochs, one, Teaching(model.params, lam, new_weight(n_new, model.rows, alpha)))
        return Model(c, params, rows, **version, steps=settings.epochs * (n_both + (n_both - n_new)))

    makers = {
        "stale": lambda: model,
        "retrain": lambda: replace(train_all(c, mixed(old), columns, settings), rows=rows),
        "fine_tune": tuned,
        "kd": distilled,
        "pooled": lambda: replace(train_all(c, mixed(transfer), columns, settings), rows=rows),
    }
    return {k: makers[k]() for k in which}


def train_counted(component: Component, cells: np.ndarray, n: np.ndarray, settings: Settings = Settings()) -> Model:  # noqa: B008
    """:func:`train_all` from the counts ``n`` of the rows' distinct values."""
    params, steps = fit_counted(component, cells, n, component.initial(np.random.default_rng(settings.seed)), settings)
    return Model(component, params, int(n.sum()), steps=steps)


def policies_counted(model: Model, cells: np.ndarray, old: np.ndarray, batch: np.ndarray, transfer: np.ndarray, settings: Settings = Settings(), lam: float = LAMBDA, alpha: str | float = "described", which: tuple[str, ...] = ("stale", "retrain", "fine_tune", "kd", "pooled")) -> dict[str, Model]:  # noqa: B008
    """:func:`policies_all` from the counts of old, new and transfer rows in each of ``cells``."""
    n_new = int(batch.sum())
    rows, c = model.rows + n_new, model.component
    version = {"version": model.version + 1, "parent": model.version}

    def updated(transfer: np.ndarray | None = None, teaching: Teaching | None = None) -> Model:
        params, steps = fit_counted(c, cells, batch, model.params, settings, transfer, teaching)
        return Model(c, params, rows, **version, steps=steps)

    makers = {
        "stale": lambda: model,
        "retrain": lambda: replace(train_counted(c, cells, old + batch, settings), rows=rows),
        "fine_tune": updated,
        "kd": lambda: updated(transfer, Teaching(model.params, lam, new_weight(n_new, model.rows, alpha))),
        "pooled": lambda: replace(train_counted(c, cells, transfer + batch, settings), rows=rows),
    }
    return {k: makers[k]() for k in which}


def at_once(spark: SparkSession, jobs: list[Callable]) -> list:
    """Results of independent trainings, each in a task of its own; they hold counts and weights, no rows."""
    return spark.sparkContext.parallelize(range(len(jobs)), len(jobs)).map(lambda i: jobs[i]()).collect()


def tune_lambda(model: Model, batch: np.ndarray, transfer: np.ndarray, validation: np.ndarray, n_new: int, grid: tuple[float, ...] = LAMBDA_GRID, settings: Settings = Settings()) -> tuple[float, dict[float, float]]:  # noqa: B008
    """The lambda with the least validation loss on old and new rows."""
    losses = {lam: float(model.component.row_loss(distil(model, batch, transfer, n_new, lam, settings=settings).params, validation).mean()) for lam in grid}
    return min(losses, key=losses.get), losses
