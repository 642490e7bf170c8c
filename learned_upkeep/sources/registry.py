"""Append-only registry of model versions, baselines and verdicts in Parquet."""

from __future__ import annotations

import json
from dataclasses import asdict

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.detect import Baseline, Verdict

VERSIONS = "component string, version int, parent int, batch_id long, rows long, names array<string>, shapes array<array<int>>, weights array<binary>, meta string"
BASELINES = "component string, version int, mean double, std double, n_boot long, sigma double, n_old long, means array<double>"
VERDICTS = "component string, batch_id long, version int, shift double, threshold double, z double, p_normal double, p_empirical double, is_ood boolean, n_old long, n_new long"


class Registry:
    """``path`` may be in any store that Spark writes to.  A version is published by one appended file."""

    def __init__(self, spark: SparkSession, path: str) -> None:
        self.spark, self.path = spark, path.rstrip("/")

    def _read(self, kind: str, schema: str) -> DataFrame:
        at = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{kind}")
        there = at.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(at)
        return self.spark.read.schema(schema).parquet(f"{self.path}/{kind}") if there else self.spark.createDataFrame([], schema)

    def _append(self, kind: str, schema: str, row: tuple) -> None:
        self.spark.createDataFrame([row], schema).coalesce(1).write.mode("append").parquet(f"{self.path}/{kind}")

    def publish(self, component: str, version: int, parent: int | None, batch_id: int, rows: int, params: dict[str, np.ndarray], meta: dict | None = None) -> bool:
        """False if this component has a version for the batch already: a replayed batch publishes nothing."""
        if self.processed(component, batch_id):
            return False
        names = sorted(params)
        shapes = [list(params[n].shape) for n in names]
        weights = [bytearray(np.ascontiguousarray(params[n], "<f8").tobytes()) for n in names]
        self._append("versions", VERSIONS, (component, version, parent, batch_id, rows, names, shapes, weights, json.dumps(meta or {})))
        return True

    def processed(self, component: str, batch_id: int) -> bool:
        return not self._read("versions", VERSIONS).where((F.col("component") == component) & (F.col("batch_id") == batch_id)).isEmpty()

    def history(self, component: str) -> DataFrame:
        return self._read("versions", VERSIONS).where(F.col("component") == component).drop("weights")

    def latest(self, component: str):
        """(version, rows, params, meta) of the newest version, or None."""
        found = self._read("versions", VERSIONS).where(F.col("component") == component).orderBy(F.desc("version")).limit(1).collect()
        if not found:
            return None
        r = found[0]
        params = {n: np.frombuffer(bytes(w), "<f8").reshape(s).copy() for n, s, w in zip(r["names"], r["shapes"], r["weights"], strict=True)}
        return r["version"], r["rows"], params, json.loads(r["meta"])

    def put_baseline(self, component: str, version: int, b: Baseline) -> None:
        self._append("baselines", BASELINES, (component, version, b.mean, b.std, b.n_boot, b.sigma, b.n_old, [float(m) for m in b.means]))

    def baseline(self, component: str, version: int) -> Baseline | None:
        found = self._read("baselines", BASELINES).where((F.col("component") == component) & (F.col("version") == version)).limit(1).collect()
        return Baseline(**{k: (tuple(v) if k == "means" else v) for k, v in found[0].asDict().items() if k not in ("component", "version")}) if found else None

    def log_verdict(self, component: str, batch_id: int, version: int, v: Verdict) -> None:
        d = asdict(v)
        self._append("verdicts", VERDICTS, (component, batch_id, version, *[d[k] for k in ("shift", "threshold", "z", "p_normal", "p_empirical", "is_ood", "n_old", "n_new")]))

    def verdicts(self, component: str) -> DataFrame:
        return self._read("verdicts", VERDICTS).where(F.col("component") == component)
