"""SQL surface: views over fixtures, and functions that answer from a model."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from ..operators.counts import ChainCounts
from ..sources.catalog import FIXTURES

COMPARISONS = {"EqualTo": "=", "GreaterThanOrEqual": ">=", "LessThanOrEqual": "<="}


def register_fixtures(spark: SparkSession, sf_dir: str) -> list[str]:
    for name, f in FIXTURES.items():
        f.build(spark, sf_dir).createOrReplaceTempView(name)
    return list(FIXTURES)


def register_model(spark: SparkSession, name: str, model: ChainCounts) -> None:
    """A view ``<name>_cells`` (columns, prob, expected rows), which answers any COUNT over the model's columns."""
    model.masses().withColumn("expected", F.col("prob") * F.lit(float(model.rows))).createOrReplaceTempView(f"{name}_cells")


def estimate_count(spark: SparkSession, name: str, condition: str) -> float:
    """COUNT(*) estimate of a condition, in Spark's own SQL grammar, over the model's columns."""
    return float(spark.table(f"{name}_cells").where(condition).agg(F.coalesce(F.sum("expected"), F.lit(0.0))).first()[0])


@udtf(returnType="n long, mean_loss double, shift double, is_ood boolean")
class DriftReport:
    """drift_report(TABLE(scored), mean, limit): one verdict row over a table with a column ``loss``."""

    def __init__(self) -> None:
        self.n, self.total, self.mean, self.limit = 0, 0.0, 0.0, 0.0

    def eval(self, row, mean: float, limit: float) -> None:
        self.n, self.total, self.mean, self.limit = self.n + 1, self.total + row["loss"], mean, limit

    def terminate(self):
        if self.n:
            shift = self.total / self.n - self.mean
            yield self.n, self.total / self.n, shift, abs(shift) > self.limit


def register_functions(spark: SparkSession) -> None:
    spark.udtf.register("drift_report", DriftReport)


def boxes_from_sql(spark: SparkSession, conditions: list[str], columns: tuple[str, ...], sizes: tuple[int, ...]) -> DataFrame:
    """Conjunctions of =, >= and <= on the columns as box queries."""
    import re

    rows = []
    for qid, text in enumerate(conditions):
        lo, hi = [0] * len(columns), [k - 1 for k in sizes]
        for part in re.split(r"\s+and\s+", text.strip(), flags=re.IGNORECASE):
            m = re.fullmatch(r"(\w+)\s*(=|>=|<=)\s*(-?\d+)", part.strip())
            if not m or m[1] not in columns:
                raise ValueError(f"only conjunctions of =, >= and <= on {columns} are understood: {part!r}")
            i, v = columns.index(m[1]), int(m[3])
            if m[2] in ("=", ">="):
                lo[i] = max(lo[i], v)
            if m[2] in ("=", "<="):
                hi[i] = min(hi[i], v)
        rows.append((qid, *[x for pair in zip(lo, hi, strict=True) for x in pair]))
    return spark.createDataFrame(rows, "qid int, " + ", ".join(f"{c}_{e} int" for c in columns for e in ("lo", "hi")))
