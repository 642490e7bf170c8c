"""Batches with and without drift."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.columns import HASH_SPACE, cut, hash_sample, position, row_hash


def ind_batch(df: DataFrame, fraction: float = 0.2, seed: int = 1) -> DataFrame:
    """A sample of a straight copy: no drift."""
    return hash_sample(df, fraction, f"ind{seed}")


def permuted_batch(df: DataFrame, columns: tuple[str, ...], fraction: float = 0.2, seed: int = 1, sort: tuple[str, ...] | None = None, descending: tuple[str, ...] = ()) -> DataFrame:
    """A sample of a copy whose ``sort`` columns (all by default) are each sorted on their own.

    Codes have small domains, so sorting is never done: a sorted column is a step function of the
    rank, given by running counts of its values (one aggregation), and only the ranks that the
    sample takes are generated.  Columns that are not sorted keep the rows of the copy in the
    order of a hash.  Every marginal of the full copy is kept.
    """
    sort = columns if sort is None else sort
    spark = df.sparkSession
    free = [c for c in columns if c not in sort]
    counts: dict[str, dict] = {c: {} for c in sort}
    if sort:
        named = F.explode(F.array(*[F.struct(F.lit(c).alias("c"), F.col(c).cast("int").alias("v")) for c in sort])).alias("s")
        for r in df.select(named).groupBy("s.c", "s.v").count().collect():  # one pass, as many rows as the domains together
            counts[r["c"]][r["v"]] = r["count"]
    n = sum(counts[sort[0]].values()) if sort else df.count()

    def value(c: str) -> Column:
        values = sorted(counts[c], key=lambda v: (v is not None, v or 0), reverse=c in descending)
        if not values:
            return F.lit(None).cast("int")
        ends = np.cumsum([counts[c][v] for v in values]).tolist()
        # a value's ranks run up to its running count
        return F.get(F.array(*[F.lit(v).cast("int") for v in values]), position(F.array(*[F.lit(e).cast("long") for e in ends]), len(ends), F.col("rank")))

    picked = row_hash(F.col("rank").cast("string"), f"ood{seed}") < F.lit(cut(fraction))
    if free:
        rows = global_rank(df.withColumn("__h", row_hash("rk", f"shuffle{seed}")), ["__h", "rk"]).where(picked)
    else:
        rows = spark.range(n).select(F.col("id").alias("rank")).where(picked)
    return rows.select(F.concat(F.lit("p|"), F.col("rank").cast("string")).alias("rk"), *[value(c).alias(c) if c in sort else F.col(c) for c in columns])


def permuted_pair(df: DataFrame, category: str, number: str, fraction: float = 0.2, seed: int = 1, descending: tuple[str, ...] = ()) -> DataFrame:
    """As :func:`permuted_batch` for one code and one real number, whose ranks need a real sort."""
    numbers = global_rank(df.select("rk", number), [number, "rk"], number in descending).drop("rk")
    codes = permuted_batch(df, (category,), 1.0, seed, descending=descending).select(F.substring("rk", 3, 20).cast("long").alias("rank"), category)
    picked = row_hash(F.col("rank").cast("string"), f"ood{seed}") < F.lit(cut(fraction))
    return numbers.where(picked).join(codes.where(picked), "rank").select(F.concat(F.lit("p|"), F.col("rank").cast("string")).alias("rk"), category, number)


def global_rank(df: DataFrame, by: list[str], descending: bool = False, parts: int | None = None) -> DataFrame:
    """Adds ``rank`` from 0 in the order of ``by`` (the first column may descend) without one task for all rows.

    Rows are range-partitioned and sorted; each partition's rows are numbered by their position, and
    partition sizes (one row each) give the offsets.
    """
    order = [F.desc(by[0]) if descending else F.asc(by[0]), *[F.asc(c) for c in by[1:]]]
    ranged = df.repartitionByRange(parts, *order) if parts else df.repartitionByRange(*order)
    numbered = ranged.sortWithinPartitions(*order).withColumn("__id", F.monotonically_increasing_id())
    numbered = numbered.checkpoint() if df.sparkSession.conf.get("spark.checkpoint.dir", None) else numbered.persist()
    part = F.shiftrightunsigned("__id", 33)
    sizes = numbered.groupBy(part.alias("__p")).agg(F.count("*").alias("__n"))
    before = sizes.select("__p", F.coalesce(F.sum("__n").over(W.partitionBy(F.lit(0)).orderBy("__p").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("__b"))
    return numbered.withColumn("__p", part).join(F.broadcast(before), "__p").withColumn("rank", F.col("__id").bitwiseAND((1 << 33) - 1) + F.col("__b")).drop("__p", "__b", "__id")


def shifted_batch(df: DataFrame, number: str, factor: float, where: Column | None = None) -> DataFrame:
    """Rows whose number is scaled, all of them or those that meet a condition."""
    new = F.col(number) * F.lit(factor)
    return df.withColumn(number, new if where is None else F.when(where, new).otherwise(F.col(number)))


def split_batches(df: DataFrame, n: int = 5, seed: int = 1) -> DataFrame:
    """Adds batch_id 0..n-1: equal ranges of a second hash."""
    return df.withColumn("batch_id", F.floor(row_hash("rk", f"split{seed}") * F.lit(n) / F.lit(HASH_SPACE)).cast("int"))


def ood_pool(df: DataFrame, columns: tuple[str, ...], share: float = 0.1, seed: int = 1) -> DataFrame:
    """Slices of ``share`` of a copy each, the first with one sorted column, the next with two, and so on; with ``level``."""
    out = None
    for k in range(1, len(columns) + 1):
        part = permuted_batch(df, columns, share, seed * 100 + k, sort=columns[:k]).withColumn("level", F.lit(k))
        out = part if out is None else out.unionByName(part)
    return out


def time_partitions(df: DataFrame, day: str, n: int = 5) -> DataFrame:
    """Adds batch_id 0..n-1: equal parts by time.  Days are counted first, so the window sees one row for each day."""
    per_day = df.groupBy(F.col(day).alias("__d")).agg(F.count("*").alias("__n"))
    w = W.partitionBy(F.lit(0))
    upto = F.sum("__n").over(w.orderBy("__d"))
    total = F.sum("__n").over(w)
    parts = per_day.select("__d", F.least(F.lit(n - 1), F.floor((upto - 1) * F.lit(n) / total)).cast("int").alias("batch_id"))
    return df.join(parts, F.col(day) == F.col("__d")).drop("__d")
