"""Regression of a number on codes, with the squared error as its loss.

The model is the mean of the number in each cell of the codes, so a fit is one aggregation and
scoring one join with the cells, broadcast up to ``MAX_CELLS`` of them.  It sees the conditional only: a batch
whose codes alone have moved does not raise its loss, one whose number depends on them otherwise does.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .counts import MAX_CELLS


@dataclass(frozen=True)
class CellMeans:
    columns: tuple[str, ...]
    target: str
    frame: DataFrame
    overall: float
    small: bool = True

    def score(self, df: DataFrame) -> DataFrame:
        """``df`` with ``loss``, the squared error.  A cell that the fit has not seen is predicted by the mean of all rows; a row without a target has no loss and counts for none."""
        cells = self.frame.select(*[F.col(c).alias(f"__{c}") for c in self.columns], "__mean")
        same = [F.col(c).eqNullSafe(F.col(f"__{c}")) for c in self.columns]
        found = df.join(F.broadcast(cells) if self.small else cells, same, "left")
        error = F.col(self.target) - F.coalesce(F.col("__mean"), F.lit(self.overall))
        return found.withColumn("loss", error * error).drop("__mean", *[f"__{c}" for c in self.columns])


def fit(df: DataFrame, columns: tuple[str, ...], target: str) -> CellMeans:
    """Means by cell of the rows that have a target."""
    frame = df.where(F.col(target).isNotNull()).groupBy(*columns).agg(F.avg(target).alias("__mean"))
    overall = df.agg(F.coalesce(F.avg(target), F.lit(0.0))).first()[0]
    return CellMeans(columns, target, frame, overall, frame.limit(MAX_CELLS + 1).count() <= MAX_CELLS)
