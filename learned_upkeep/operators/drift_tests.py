"""Two-sample tests that the loss-based test is compared with, and the dependence that drift can show in."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def ks(old: DataFrame, new: DataFrame, columns: tuple[str, ...]) -> DataFrame:
    """(col, ks): largest gap of the two distribution functions of each column, from counts by value."""
    long = lambda df, side: df.select(F.lit(side).alias("side"), F.explode(F.array(*[F.struct(F.lit(c).alias("col"), F.col(c).cast("double").alias("v")) for c in columns])).alias("s")).select("side", "s.*")
    counted = long(old, 0).unionByName(long(new, 1)).groupBy("col", "v").agg(F.count_if(F.col("side") == 0).alias("o"), F.count_if(F.col("side") == 1).alias("n"))
    whole, run = W.partitionBy("col"), W.partitionBy("col").orderBy("v")
    share = lambda c: F.sum(c).over(run) / F.sum(c).over(whole)
    return counted.select("col", F.abs(share("o") - share("n")).alias("gap")).groupBy("col").agg(F.round(F.max("gap"), 6).alias("ks"))


def mmd(old: DataFrame, new: DataFrame, columns: tuple[str, ...], gamma: float = 0.1, max_rows: int = 200) -> DataFrame:
    """Squared maximum mean discrepancy with an RBF kernel between capped samples (at most ``max_rows`` each, so pairs are bounded)."""
    a = old.orderBy("rk").limit(max_rows).select(F.lit(0).alias("s"), *columns)
    b = new.orderBy("rk").limit(max_rows).select(F.lit(1).alias("s"), *columns)
    x = a.unionByName(b)
    y = x.select(*[F.col(c).alias(f"{c}_2") for c in ("s", *columns)])
    square = reduce(lambda p, q: p + q, [(F.col(c) - F.col(f"{c}_2")) * (F.col(c) - F.col(f"{c}_2")) for c in columns])
    k = F.exp(-F.lit(gamma) * square.cast("double"))
    pairs = x.crossJoin(F.broadcast(y)).groupBy("s", "s_2").agg(F.avg(k).alias("m"))
    return pairs.agg(F.round(F.sum(F.when(F.col("s") == F.col("s_2"), F.col("m")).otherwise(-F.col("m"))), 6).alias("mmd2"))


def mmd_cells(old: DataFrame, new: DataFrame, columns: tuple[str, ...], gamma: float = 0.1) -> DataFrame:
    """The same statistic over all rows of both sides: a double sum over the cells that occur, not over rows."""
    whole = W.partitionBy("s")
    both = old.groupBy(*columns).agg(F.count("*").alias("n")).withColumn("s", F.lit(1)).unionByName(new.groupBy(*columns).agg(F.count("*").alias("n")).withColumn("s", F.lit(-1)))
    # the two shares of a cell enter with opposite signs
    x = both.withColumn("w", F.col("s") * F.col("n") / F.sum("n").over(whole)).groupBy(*columns).agg(F.sum("w").alias("w"))
    y = x.select(*[F.col(c).alias(f"{c}_2") for c in ("w", *columns)])
    square = reduce(lambda p, q: p + q, [(F.col(c) - F.col(f"{c}_2")) * (F.col(c) - F.col(f"{c}_2")) for c in columns])
    return x.crossJoin(F.broadcast(y)).agg(F.round(F.sum(F.col("w") * F.col("w_2") * F.exp(-F.lit(gamma) * square.cast("double"))), 6).alias("mmd2"))


def dependence(df: DataFrame, columns: tuple[str, ...]) -> DataFrame:
    """(a, b, corr): correlation of each pair of columns in one pass."""
    pairs = [(a, b) for i, a in enumerate(columns) for b in columns[i + 1 :]]
    row = df.agg(*[F.round(F.corr(F.col(a).cast("double"), F.col(b).cast("double")), 6).alias(f"c{i}") for i, (a, b) in enumerate(pairs)])
    parts = F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), F.col(f"c{i}").alias("corr")) for i, (a, b) in enumerate(pairs)])
    return row.select(F.explode(parts).alias("p")).select("p.*")


def confidence(scored: DataFrame) -> DataFrame:
    """Mean confidence of a classifier's predictions, from a column of class probabilities."""
    return scored.agg(F.avg(F.array_max("probabilities")).alias("confidence"))
