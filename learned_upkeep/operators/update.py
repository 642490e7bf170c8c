"""Branching and update policies on the count model; the networks use the same weights and names."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.columns import hash_sample
from ..sources.catalog import Fixture
from . import counts

LAMBDA_GRID = (9 / 10, 5 / 6, 1 / 4, 1 / 2)
LAMBDA = 5 / 6
TRANSFER = 0.1
ALPHA_MODES = ("described", "printed", "mass")


def new_weight(n_new: int, n_old: int, mode: str | float = "described") -> float:
    """The weight of the batch term.

    ``described``: batch size over old size, at most 1.  ``printed``: one minus that.  ``mass``: the
    batch's share of all rows.  A number is taken as it is.
    """
    if not isinstance(mode, str):
        return float(mode)
    ratio = min(1.0, n_new / max(1, n_old))
    return {"described": ratio, "printed": 1 - ratio, "mass": n_new / max(1, n_new + n_old)}[mode]


def transfer_set(old: DataFrame, fraction: float = TRANSFER, seed: int = 1) -> DataFrame:
    """A sample of all older rows; nested over time, since a row's hash never changes."""
    return hash_sample(old, fraction, f"transfer{seed}")


@dataclass(frozen=True)
class Sizes:
    old: int
    new: int


def keep(model: counts.ChainCounts, n_new: int) -> counts.ChainCounts:
    """No drift: the same model with the new cardinality."""
    return model.with_rows(model.rows + n_new)


def merge_frequencies(old: DataFrame, batch: DataFrame, category: str) -> DataFrame:
    """Frequency tables of old rows and batch, merged: (category, n)."""
    both = counts.cells(old, (category,)).unionByName(counts.cells(batch, (category,)))
    return both.groupBy(category).agg(F.sum("n").alias("n"))


def policies(fixture: Fixture, old: DataFrame, batch: DataFrame, lam: float = LAMBDA, seed: int = 1, which: tuple[str, ...] | None = None) -> dict[str, counts.ChainCounts]:
    """Every policy's model after one batch, from three tables of cells (old, transfer, batch)."""
    co, cb = counts.cells(old, fixture.columns).persist(), counts.cells(batch, fixture.columns).persist()
    ct = counts.cells(transfer_set(old, seed=seed), fixture.columns).persist()
    n_old, n_new = (c.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0] for c in (co, cb))
    total = n_old + n_new
    added = lambda a, b: a.unionByName(b).groupBy(*fixture.columns).agg(F.sum("n").alias("n"))
    base = counts.fit_cells(co, fixture, counts.SMOOTHING, n_old)
    makers = {
        "base": lambda: base,
        "stale": lambda: base,
        "stale_refreshed": lambda: keep(base, n_new),
        "retrain": lambda: counts.fit_cells(added(co, cb), fixture, counts.SMOOTHING, total),
        "fine_tune": lambda: counts.fine_tune(base, cb, 1.0, total),
        "fine_tune_small": lambda: counts.fine_tune(base, cb, n_new / max(1, n_old), total),
        "pooled": lambda: counts.fit_cells(added(ct, cb), fixture, counts.SMOOTHING, total),
        **{f"kd_{m}": (lambda m=m: counts.distil(base, ct, cb, lam, new_weight(n_new, n_old, m), total)) for m in ALPHA_MODES},
        "no_teacher": lambda: counts.distil(base, ct, cb, 0.0, new_weight(n_new, n_old), total),
    }
    return {k: makers[k]() for k in which or makers}


def lambda_grid(fixture: Fixture, old: DataFrame, batch: DataFrame, grid: tuple[float, ...] = LAMBDA_GRID, seed: int = 1) -> DataFrame:
    """(lam, loss_old, loss_new): the mean loss on all old rows and on the batch for each lambda; the least sum wins."""
    out = None
    for lam in grid:
        m = policies(fixture, old, batch, lam, seed, ("kd_described",))["kd_described"]
        loss = lambda df: counts.cells(df, fixture.columns).join(F.broadcast(m.losses()), list(fixture.columns)).agg((F.sum(F.col("n") * F.col("loss")) / F.sum("n")).alias("l"))  # noqa: B023, E731
        row = loss(old).select(F.lit(round(lam, 6)).alias("lam"), F.col("l").alias("loss_old")).crossJoin(loss(batch).select(F.col("l").alias("loss_new")))
        out = row if out is None else out.unionByName(row)
    return out
