"""The controller: detect, branch, update, and a new baseline for each batch."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame

from ..functions.columns import hash_sample
from ..nn.training import Component, Settings, matrix, score
from ..operators import detect, networks
from ..operators.update import LAMBDA, TRANSFER
from ..sources.registry import Registry


@dataclass(frozen=True)
class Policy:
    """What the controller does; the defaults are the published settings."""

    transfer: float = TRANSFER
    lam: float = LAMBDA
    alpha: str = "described"
    mode: str = "size_matched"
    tail: str = "two_sided"
    on_ind: str = "keep"  # or "fine_tune"
    min_batch_rows: int = 1000
    cap_rows: int = 200_000
    settings: Settings = Settings()


@dataclass(frozen=True)
class State:
    """The model, its baseline, and all rows so far."""

    model: networks.Model
    baseline: detect.Baseline
    old: DataFrame
    columns: tuple[str, ...]


def bounded(df: DataFrame, columns: tuple[str, ...], cap: int, seed: str, rows: int) -> object:
    """At most about ``cap`` rows as a matrix: a hash sample where there are more."""
    return matrix(hash_sample(df, min(1.0, cap / max(1, rows)), seed) if rows > cap else df, list(columns), int(cap * 1.2) + 1000)


def offline(model: networks.Model, old: DataFrame, columns: tuple[str, ...], rows: int, policy: Policy) -> detect.Baseline:
    """Scores a bounded sample of old rows and bootstraps its mean loss."""
    share = min(1.0, policy.cap_rows / max(1, rows))
    sample = hash_sample(old, share, "baseline") if share < 1 else old
    return detect.offline(score(sample.select("rk", *columns), model.component, model.params, list(columns)))


def start(component: Component, old: DataFrame, columns: tuple[str, ...], policy: Policy = Policy()) -> State:  # noqa: B008
    rows = old.count()
    model = networks.train(component, bounded(old, columns, policy.cap_rows, "train", rows), rows, policy.settings)
    return State(model, offline(model, old, columns, rows, policy), old, columns)


def step(state: State, batch: DataFrame, policy: Policy = Policy(), registry: Registry | None = None, batch_id: int = 0) -> tuple[State, detect.Verdict | None]:  # noqa: B008
    """One insertion.  A batch below ``min_batch_rows`` is left to be merged into the next one (verdict None)."""
    n_new = batch.count()
    if n_new < policy.min_batch_rows:
        return state, None
    columns, model = state.columns, state.model
    sample = batch if n_new <= policy.cap_rows else hash_sample(batch, policy.cap_rows / n_new, "test")
    verdict = detect.test_batch(score(sample.select("rk", *columns), model.component, model.params, list(columns)), state.baseline, policy.mode, policy.tail)
    new = lambda: bounded(batch, columns, policy.cap_rows, "train", n_new)
    if verdict.is_ood:
        share = min(policy.transfer, policy.cap_rows / max(1, model.rows))
        transfer = matrix(hash_sample(state.old, share, "transfer1"), list(columns), int(policy.cap_rows * 1.2) + 1000)
        updated = networks.distil(model, new(), transfer, n_new, policy.lam, policy.alpha, policy.settings)
    elif policy.on_ind == "fine_tune":
        updated = networks.fine_tune(model, new(), n_new, policy.settings)
    else:
        updated = replace(model, rows=model.rows + n_new)
    old = state.old.unionByName(batch.select(*state.old.columns))
    # without a new model the baseline stays valid: nothing is bootstrapped again
    baseline = state.baseline if updated.params is model.params else offline(updated, old, columns, updated.rows, policy)
    if registry:
        registry.log_verdict(model.component.name, batch_id, model.version, verdict)
        if registry.publish(model.component.name, updated.version, updated.parent, batch_id, updated.rows, updated.params) and updated.params is not model.params:
            registry.put_baseline(model.component.name, updated.version, baseline)
    return State(updated, baseline, old, columns), verdict
