"""Join operators around the methods, and the delta of a join under insertion."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.columns import hash_sample

STRATEGIES = {"auto": None, "broadcast": "broadcast", "sort_merge": "merge", "shuffle_hash": "shuffle_hash"}
#: Rows under which a dimension may be broadcast without a look at its statistics.
LOOKUP_ROWS = 1_000_000


def equi(a: DataFrame, b: DataFrame, on: list[str], how: str = "inner", strategy: str = "auto") -> DataFrame:
    hint = STRATEGIES[strategy]
    return a.join(b.hint(hint) if hint else b, on, how)


def lookup(df: DataFrame, dimension: DataFrame, on: list[str]) -> DataFrame:
    """Left join with a dimension: broadcast if it is small, sort-merge otherwise."""
    small = dimension.limit(LOOKUP_ROWS + 1).count() <= LOOKUP_ROWS
    return df.join(F.broadcast(dimension) if small else dimension.hint("merge"), on, "left")


def in_range(df: DataFrame, intervals: DataFrame, value: str, lo: str, hi: str, bucket: float) -> DataFrame:
    """Rows with their intervals [lo, hi]: an equi-join on buckets of the axis instead of comparing all pairs."""
    cell = lambda c: F.floor(c / F.lit(bucket))
    spread = intervals.withColumn("__b", F.explode(F.sequence(cell(F.col(lo)), cell(F.col(hi)))))
    return df.withColumn("__b", cell(F.col(value))).join(spread, "__b").where(F.col(value).between(F.col(lo), F.col(hi))).drop("__b")


def as_of(df: DataFrame, versions: DataFrame, by: list[str], time: str, value: str, bucket: str = "1 day") -> DataFrame:
    """Each row with the last version at or before its time, by a union and a running last value.

    Keys are cut into buckets of time, so a hot key spreads over as many tasks as it has buckets.  The
    value that holds at a bucket's start is carried into it: one small row for each key and bucket.
    Of versions at one time the largest value holds; versions without time or value never do.
    """
    cut = F.window(time, bucket)["start"]
    key = [*by, "__b"]
    # a time window drops rows without a time, and those have no version
    r = df.where(F.col(time).isNotNull()).withColumn("__b", cut).withColumn("__v", F.lit(None).cast(versions.schema[value].dataType)).withColumn("__row", F.lit(2))
    v = versions.where(F.col(time).isNotNull() & F.col(value).isNotNull()).select(*by, time, F.col(value).alias("__v")).withColumn("__b", cut)
    last = v.groupBy(*key).agg(F.max_by("__v", F.struct(time, "__v")).alias("__v"))
    # one row a key and bucket; its own versions come after its start, so only earlier buckets count
    met = last.unionByName(r.select(*key, "__v").distinct()).groupBy(*key).agg(F.max("__v").alias("__v"))
    earlier = W.partitionBy(*by).orderBy("__b").rowsBetween(W.unboundedPreceding, -1)
    carried = met.select(*key, F.last("__v", ignorenulls=True).over(earlier).alias("__v"), F.lit(0).alias("__row")).where(F.col("__v").isNotNull())
    both = r.unionByName(v.withColumn("__row", F.lit(1)), allowMissingColumns=True).unionByName(carried, allowMissingColumns=True)
    running = W.partitionBy(*key).orderBy(F.when(F.col("__row") > 0, F.col(time)).asc_nulls_first(), "__row", "__v").rowsBetween(W.unboundedPreceding, 0)
    out = both.withColumn(value, F.last("__v", ignorenulls=True).over(running)).where("__row = 2").drop("__b", "__v", "__row")
    return out.unionByName(df.where(F.col(time).isNull()).withColumn(value, F.lit(None).cast(versions.schema[value].dataType)))


def interval(a: DataFrame, b: DataFrame, on: list[str], a_time: str, b_time: str, seconds: int) -> DataFrame:
    """Pairs of equal keys where b's time lies within ``seconds`` after a's.

    Buckets of that width join the keys: a row of ``a`` meets its own bucket and the next, so a hot key costs its close pairs only.
    """
    width = f"{max(1, seconds)} seconds"
    near = F.explode(F.array("__b", F.col("__b") + F.make_interval(secs=F.lit(max(1, seconds)))))
    left = a.withColumn("__b", F.window(a_time, width)["start"]).withColumn("__b", near)
    right = b.withColumn("__b", F.window(b_time, width)["start"])
    later = F.col(b_time).between(F.col(a_time), F.col(a_time) + F.make_interval(secs=F.lit(seconds)))
    return left.join(right, [*on, "__b"]).where(later).drop("__b")


def grow(relation: DataFrame, batch: DataFrame) -> DataFrame:
    return relation.unionByName(batch)


def bag_difference(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.exceptAll(b)


def delta(fact_batch: DataFrame, *dimensions: tuple[DataFrame, Column]) -> DataFrame:
    """New rows of a join when only the first table grows: its batch joined with the others as they stand."""
    out = fact_batch
    for table, on in dimensions:
        out = out.join(table, on)
    return out


def delta_two(a: DataFrame, a_new: DataFrame, b: DataFrame, b_new: DataFrame, on: list[str]) -> DataFrame:
    """New rows of a join when both tables grow: a's batch with the old b, then the grown a with b's batch."""
    return a_new.join(b, on).unionByName(grow(a, a_new).join(b_new, on))


def delta_many(tables: list[tuple[DataFrame, DataFrame]], on: list[list[str]]) -> DataFrame:
    """New rows of a join of any number of tables when each may grow.

    ``tables`` holds (old, batch) in the order of the join, and ``on`` the columns that join each
    table but the first to those before it.  The batch of table i meets the grown tables before it
    and the old ones after it, so each new row comes once and the old join is never read again.
    """
    out = None
    for i, (_, batch) in enumerate(tables):
        sides = [grow(*t) for t in tables[:i]] + [batch] + [old for old, _ in tables[i + 1 :]]
        part = sides[0]
        for side, columns in zip(sides[1:], on, strict=True):
            part = part.join(side, columns)
        out = part if out is None else out.unionByName(part)
    return out


def join_sample(fact: DataFrame, fraction: float, seed: int, *dimensions: tuple[DataFrame, Column]) -> DataFrame:
    """A sample of a foreign-key join without the join of all rows: fact rows are sampled first."""
    return delta(hash_sample(fact, fraction, f"join{seed}"), *dimensions)
