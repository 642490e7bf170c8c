"""Structured Streaming: upkeep per micro-batch, drift curves, and a stateful monitor per key."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.upkeep import Policy, State, step
from ..sources.registry import Registry


def file_stream(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


class Upkeep:
    """``foreachBatch`` target: each micro-batch is an insertion.

    A batch that is too small waits with the next one.  Delivery is at least once, so a batch whose
    number the registry has for this component is skipped.
    """

    def __init__(self, state: State, registry: Registry, policy: Policy = Policy()) -> None:  # noqa: B008
        self.state, self.registry, self.policy = state, registry, policy
        self.pending: DataFrame | None = None

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        if self.registry.processed(self.state.model.component.name, batch_id):
            return
        rows = batch.select("rk", *self.state.columns)
        rows = rows if self.pending is None else self.pending.unionByName(rows)
        rows = rows.persist()
        self.state, verdict = step(self.state, rows, self.policy, self.registry, batch_id)
        self.pending = rows if verdict is None else None

    def run(self, stream: DataFrame, checkpoint: str):
        return stream.writeStream.foreachBatch(self).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def drift_curve(scored: DataFrame, window: str = "1 day", slide: str | None = None, late: str | None = "1 hour", key: str | None = None) -> DataFrame:
    """Mean loss by event-time window; rows later than ``late`` are left out.  None keeps a watermark that is set already."""
    w = F.window("ts", window, slide) if slide else F.window("ts", window)
    by = [w, *([F.col(key)] if key else [])]
    out = (scored.withWatermark("ts", late) if late else scored).groupBy(*by).agg(F.avg("loss").alias("mean_loss"), F.stddev_pop("loss").alias("std_loss"), F.count("*").alias("n"))
    return out.select(F.col("window.start").alias("start"), F.col("window.end").alias("end"), *([key] if key else []), "mean_loss", "std_loss", "n")


def replayed(aggregated: DataFrame) -> DataFrame:
    """What a streaming aggregation holds when all files have been read; the result has a row for each window."""
    name = f"replay_{uuid.uuid4().hex}"
    spark = aggregated.sparkSession
    writer = aggregated.writeStream.format("memory").queryName(name).outputMode("complete").trigger(availableNow=True)
    shared = spark.conf.get("spark.checkpoint.dir", None)
    (writer.option("checkpointLocation", f"{shared.rstrip('/')}/{name}") if shared else writer).start().awaitTermination()
    return spark.table(name)


def deduplicated(events: DataFrame, key: str = "event_id", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def joined_insertions(clicks: DataFrame, purchases: DataFrame, late: str = "1 hour") -> DataFrame:
    """New rows of a joined relation as a stream: purchases within an hour of a click of the same user."""
    c = clicks.select(F.col("user_id").alias("c_user"), F.col("ts").alias("click_ts")).withWatermark("click_ts", late)
    p = purchases.select(F.col("user_id").alias("p_user"), F.col("ts").alias("purchase_ts"), "value").withWatermark("purchase_ts", late)
    return c.join(p, F.expr("c_user = p_user AND purchase_ts >= click_ts AND purchase_ts <= click_ts + interval 1 hour"))


def keyed_monitor(scored: DataFrame, key: str, mean: float, std: float, k: float = 2.0, min_rows: int = 100) -> DataFrame:
    """A verdict for a key each time ``min_rows`` of its rows have come: running count and sum of losses are the state."""

    def run(name: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n, total = state.get if state.exists else (0, 0.0)
        for f in frames:
            n, total = n + len(f), total + float(f["loss"].sum())
        if n >= min_rows:
            shift = total / n - mean
            yield pd.DataFrame({"key": [name[0]], "n": [n], "shift": [shift], "is_ood": [bool(abs(shift) > k * std / n**0.5)]})
            n, total = 0, 0.0
        state.update((n, total))

    return scored.groupBy(key).applyInPandasWithState(run, "key string, n long, shift double, is_ood boolean", "n long, total double", "append", "NoTimeout")
