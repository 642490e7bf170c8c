"""The saturated count model: chained conditional counts, the optimum that an unlimited autoregressive net reaches.

A model is a table over the joint domain: one row for each cell, with the conditional probability
``p1 … pm`` of each column's code given the codes before it.  Fitting, scoring and every update
policy are aggregations of the data to cells followed by arithmetic on that table, so the cost after
one aggregation doesn't depend on the number of rows.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, replace
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..sources.catalog import Fixture

SMOOTHING = 0.1
#: Least probability of a code, and the loss of a value that no domain holds.
FLOOR = 1e-12
UNSEEN_LOSS = -math.log(FLOOR)
#: Largest joint domain that is laid out as a table of cells.
MAX_CELLS = 1_000_000


def cells(df: DataFrame, columns: tuple[str, ...], name: str = "n") -> DataFrame:
    """Rows aggregated to cells: (columns, n)."""
    return df.groupBy(*columns).agg(F.count("*").alias(name))


def marginals(df: DataFrame, columns: tuple[str, ...], sets: list[tuple[str, ...]] | None = None) -> DataFrame:
    """Counts of several column subsets in one pass (all subsets by default), with grouping_id."""
    if sets is None:
        return df.cube(*columns).agg(F.count("*").alias("n"), F.grouping_id().alias("gid"))
    return df.groupingSets([[F.col(c) for c in s] for s in sets], *[F.col(c) for c in columns]).agg(F.count("*").alias("n"), F.grouping_id().alias("gid"))


def grid(spark, columns: tuple[str, ...], sizes: tuple[int, ...]) -> DataFrame:
    """Every cell of the joint domain, from one number that is taken apart; at most MAX_CELLS."""
    total = reduce(lambda a, b: a * b, sizes, 1)
    if total > MAX_CELLS:
        raise ValueError(f"{total} cells; take fewer or coarser columns, or a network")
    out, below = [], total
    for c, k in zip(columns, sizes, strict=True):
        below //= k
        out.append(F.floor(F.col("id") / below % k).cast("int").alias(c))
    return spark.range(0, total, 1, max(1, total // 100_000)).select(*out)


@dataclass(frozen=True)
class ChainCounts:
    """Immutable: ``frame`` has the columns and p1 … pm; ``rows`` is the cardinality that estimates are scaled by."""

    fixture: Fixture
    frame: DataFrame
    rows: int
    kind: str = "nll"

    @property
    def levels(self) -> list[str]:
        return [f"p{i + 1}" for i in range(len(self.fixture.columns))]

    def log_probability(self) -> Column:
        return reduce(lambda a, b: a + b, [F.log(F.greatest(F.col(p), F.lit(FLOOR))) for p in self.levels])

    def losses(self) -> DataFrame:
        """(columns, loss): the loss of a row depends on its cell only."""
        return self.frame.select(*self.fixture.columns, (-self.log_probability()).alias("loss"))

    def score(self, df: DataFrame) -> DataFrame:
        """``df`` with a column ``loss``; the table of cells is broadcast, since its size is bounded.

        A row with a null or a value outside the domains has probability 0, so it takes the loss of the
        floor and stays: new categories are drift that the test has to see.
        """
        return df.join(F.broadcast(self.losses()), list(self.fixture.columns), "left").withColumn("loss", F.coalesce("loss", F.lit(UNSEEN_LOSS)))

    def score_columns(self, df: DataFrame) -> DataFrame:
        """``df`` with l1 … lm: the loss of each column given those before it."""
        parts = self.frame.select(*self.fixture.columns, *[(-F.log(F.greatest(F.col(p), F.lit(FLOOR)))).alias(f"l{i + 1}") for i, p in enumerate(self.levels)])
        out = df.join(F.broadcast(parts), list(self.fixture.columns), "left")
        return out.withColumns({f"l{i + 1}": F.coalesce(f"l{i + 1}", F.lit(UNSEEN_LOSS)) for i in range(len(self.levels))})

    def masses(self) -> DataFrame:
        """(columns, prob): the probability of each cell."""
        return self.frame.select(*self.fixture.columns, F.exp(self.log_probability()).alias("prob"))

    def with_rows(self, rows: int) -> ChainCounts:
        return replace(self, rows=rows)


def _prefix_sums(frame: DataFrame, columns: tuple[str, ...], value: str) -> list[Column]:
    """Sums of a value by the first 0, 1, … columns."""
    return [F.sum(value).over(W.partitionBy(F.lit(0), *columns[:i])) for i in range(len(columns) + 1)]


def _on_grid(fixture: Fixture, **counted: DataFrame) -> DataFrame:
    """The grid with one count column for each table of cells."""
    spark = next(iter(counted.values())).sparkSession
    out = grid(spark, fixture.columns, fixture.sizes)
    for name, c in counted.items():
        out = out.join(F.broadcast(c.withColumnRenamed("n", name)), list(fixture.columns), "left").withColumn(name, F.coalesce(F.col(name), F.lit(0)).cast("double"))
    return out


def fit(df: DataFrame, fixture: Fixture, smoothing: float = SMOOTHING, rows: int | None = None) -> ChainCounts:
    counted = cells(df, fixture.columns)
    return fit_cells(counted, fixture, smoothing, df.count() if rows is None else rows)


def fit_cells(counted: DataFrame, fixture: Fixture, smoothing: float, rows: int) -> ChainCounts:
    g = _on_grid(fixture, n=counted)
    sums = _prefix_sums(g, fixture.columns, "n")
    g = g.select("*", *[s.alias(f"__s{i}") for i, s in enumerate(sums)])
    p = [((F.col(f"__s{i + 1}") + smoothing) / (F.col(f"__s{i}") + smoothing * k)).alias(f"p{i + 1}") for i, k in enumerate(fixture.sizes)]
    return ChainCounts(fixture, g.select(*fixture.columns, *p), rows)


def distil(teacher: ChainCounts, transfer: DataFrame, batch: DataFrame, lam: float, w_new: float, rows: int) -> ChainCounts:
    """The minimiser of the combined update loss at temperature 1.

    In a context that the transfer set or the batch has, a code's probability is the weighted mean of
    the teacher's probability (weight lam on transfer rows), the transfer rows' and the batch's own
    shares.  In other contexts the teacher's stays.  ``transfer`` and ``batch`` are tables of cells.
    """
    columns = teacher.fixture.columns
    g = _on_grid(teacher.fixture, tr=transfer, up=batch).join(teacher.frame, list(columns))
    tr, up = _prefix_sums(g, columns, "tr"), _prefix_sums(g, columns, "up")
    g = g.select("*", *[s.alias(f"__t{i}") for i, s in enumerate(tr)], *[s.alias(f"__u{i}") for i, s in enumerate(up)])
    wo, wn = (F.lit(1.0 - w_new) / F.greatest(F.col("__t0"), F.lit(1.0))), (F.lit(w_new) / F.greatest(F.col("__u0"), F.lit(1.0)))
    out = []
    for i in range(len(columns)):
        p = F.col(f"p{i + 1}")
        top = wo * (F.lit(lam) * F.col(f"__t{i}") * p + F.lit(1.0 - lam) * F.col(f"__t{i + 1}")) + wn * F.col(f"__u{i + 1}")
        bottom = wo * F.col(f"__t{i}") + wn * F.col(f"__u{i}")
        out.append(F.when(bottom > 0, top / bottom).otherwise(p).alias(f"p{i + 1}"))
    return ChainCounts(teacher.fixture, g.select(*columns, *out), rows)


def fine_tune(model: ChainCounts, batch: DataFrame, rate: float, rows: int, smoothing: float = SMOOTHING) -> ChainCounts:
    """A step of size ``rate`` from the model towards the batch's own optimum (1 reaches it)."""
    new = fit_cells(batch, model.fixture, smoothing, rows).frame
    columns = list(model.fixture.columns)
    both = model.frame.join(new.select(*columns, *[F.col(p).alias(f"q{p}") for p in model.levels]), columns)
    return ChainCounts(model.fixture, both.select(*columns, *[((1.0 - rate) * F.col(p) + rate * F.col(f"q{p}")).alias(p) for p in model.levels]), rows)
