"""Accuracy and cost measures."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.columns import q_error, relative_error

QUANTILES = (0.5, 0.95, 0.99)


def q_errors(estimates: DataFrame, truths: DataFrame, by: tuple[str, ...] = ("qid",)) -> DataFrame:
    """Joins (…, estimate) with (qid, truth) and adds q_error."""
    return estimates.join(truths, list(by)).withColumn("q_error", q_error(F.col("estimate"), F.col("truth")))


def relative_errors(estimates: DataFrame, truths: DataFrame, by: tuple[str, ...] = ("qid",)) -> DataFrame:
    return estimates.join(truths, list(by)).withColumn("rel_error", relative_error(F.col("estimate"), F.col("truth")))


def summary(errors: DataFrame, value: str = "q_error", by: tuple[str, ...] = ("policy",), approximate: bool = False, digits: int = 4) -> DataFrame:
    """median, p95, p99, max, mean per group; ``approximate`` keeps a sketch instead of all values."""
    quantile = (lambda p: F.percentile_approx(value, p)) if approximate else (lambda p: F.percentile(value, F.lit(p)))
    aggs = [F.round(quantile(p), digits).alias(n) for p, n in zip(QUANTILES, ("median", "p95", "p99"), strict=True)]
    return errors.groupBy(*by).agg(*aggs, F.round(F.max(value), digits).alias("max"), F.round(F.avg(value), digits).alias("mean"), F.count(value).alias("n"))


def transfer(errors: DataFrame, before: DataFrame, after: DataFrame, by: tuple[str, ...] = ("policy",)) -> DataFrame:
    """Mean q-error over all (at), changed (fwt) and unchanged (bwt) queries, and their numbers."""
    b = before.select("qid", F.col("truth").alias("__b"))
    groups = after.join(b, "qid").select("qid", (F.col("truth") != F.col("__b")).alias("changed"))
    e = errors.join(groups, "qid")
    return e.groupBy(*by).agg(
        F.round(F.avg("q_error"), 4).alias("at"), F.round(F.avg(F.when(F.col("changed"), F.col("q_error"))), 4).alias("fwt"),
        F.round(F.avg(F.when(~F.col("changed"), F.col("q_error"))), 4).alias("bwt"), F.count_if("changed").alias("n_changed"), F.count("*").alias("n"),
    )


def changed_share(before: DataFrame, after: DataFrame) -> DataFrame:
    """Percent of queries whose true answer changed."""
    b = before.select("qid", F.col("truth").alias("__b"))
    return after.join(b, "qid").agg(F.round(100 * F.avg(F.when(F.col("truth") != F.col("__b"), 1.0).otherwise(0.0)), 4).alias("pct_changed"), F.count("*").alias("n"))


def loglik_old_new(scored_old: DataFrame, scored_new: DataFrame) -> DataFrame:
    """Plain average of the mean log-likelihoods of an old and a new sample."""
    o, n = scored_old.agg((-F.avg("loss")).alias("old")), scored_new.agg((-F.avg("loss")).alias("new"))
    return o.crossJoin(n).select(F.round((F.col("old") + F.col("new")) / 2, 6).alias("loglik"))  # one row each


def loss_table(scored: dict[str, DataFrame]) -> DataFrame:
    """One row with the mean loss of each source."""
    out = None
    for name, df in scored.items():
        part = df.select(F.lit(name).alias("source"), "loss")
        out = part if out is None else out.unionByName(part)
    return out.groupBy("source").agg(F.round(F.avg("loss"), 6).alias("mean_loss"), F.count("*").alias("n"))


def detector_rates(verdicts: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """fpr over batches with truth false, fnr over those with truth true; optionally by level."""
    return verdicts.groupBy(*by).agg(
        F.round(F.avg(F.when(~F.col("truth"), F.col("fired").cast("double"))), 4).alias("fpr"),
        F.round(F.avg(F.when(F.col("truth"), 1 - F.col("fired").cast("double"))), 4).alias("fnr"), F.count("*").alias("n"),
    )


def micro_f1(predictions: DataFrame, label: str = "label") -> float:
    """Micro-averaged F1, which is accuracy where each row has one label."""
    return predictions.agg(F.avg((F.col("prediction") == F.col(label)).cast("double"))).first()[0]


def timed(work: Callable[[], object]) -> tuple[object, float]:
    began = time.perf_counter()
    return work(), time.perf_counter() - began


def speedup(retrain: float, update: float) -> float:
    return retrain / update if update else float("inf")


def model_bytes(parameters: dict) -> int:
    return int(sum(p.nbytes for p in parameters.values()))
