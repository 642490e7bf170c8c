"""Query workloads and their exact answers.

A query is a box: for each column the codes from ``<c>_lo`` to ``<c>_hi``.  Equality, at-least and
at-most predicates are boxes too, and a column without a predicate spans its domain.  Truth and
estimates are both sums over cells, so a workload costs one aggregation of the data, however many
queries it has.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.columns import HASH_SPACE, position, row_hash, zero
from ..sources.catalog import Fixture

QUERIES = 2000
#: Domains below this size take equality only.
EQUALITY_BELOW = 10


def _unit(what: str, seed: int) -> Column:
    return row_hash(F.concat_ws("|", F.lit(what), "qid"), seed)


def anchors(df: DataFrame, n: int, seed: int = 1) -> DataFrame:
    """``n`` rows drawn by hash (a top-k, merged from partitions), numbered by qid from 0."""
    from pyspark.sql import Window as W

    top = df.withColumn("__h", row_hash("rk", f"query{seed}")).orderBy("__h", "rk").limit(n)
    return top.withColumn("qid", F.row_number().over(W.orderBy("__h", "rk")) - 1).drop("__h")


def ce_queries(df: DataFrame, fixture: Fixture, n: int = QUERIES, min_filters: int = 2, seed: int = 1) -> DataFrame:
    """(qid, per column lo and hi): a random number of filters from ``min_filters`` to all columns, anchored at a row."""
    m = len(fixture.columns)
    a = anchors(df, n, seed)
    wanted = (_unit("count", seed) % (m - min_filters + 1) + min_filters).cast("int")
    order = F.array_sort(F.array(*[F.struct(_unit(f"pick{c}", seed).alias("h"), F.lit(i).alias("i")) for i, c in enumerate(fixture.columns)]))
    a = a.withColumn("__wanted", wanted).withColumn("__chosen", F.slice(F.transform(order, lambda s: s["i"]), F.lit(1), F.col("__wanted")))
    out = []
    for i, (c, k) in enumerate(zip(fixture.columns, fixture.sizes, strict=True)):
        used = F.array_contains("__chosen", i)
        op = F.lit(0) if k < EQUALITY_BELOW else _unit(f"op{c}", seed) % 3  # 0 equal, 1 at least, 2 at most
        out += [
            F.when(used & (op != 2), F.col(c)).otherwise(0).cast("int").alias(f"{c}_lo"),
            F.when(used & (op != 1), F.col(c)).otherwise(k - 1).cast("int").alias(f"{c}_hi"),
        ]
    return a.select("qid", *out)


def inside(columns: tuple[str, ...]) -> Column:
    return reduce(lambda a, b: a & b, [F.col(c).between(F.col(f"{c}_lo"), F.col(f"{c}_hi")) for c in columns])


def over_cells(queries: DataFrame, cells: DataFrame, columns: tuple[str, ...], value: str, out: str) -> DataFrame:
    """(qid, out): sums of a cell value over each query's box; queries are broadcast (a workload has some thousand)."""
    hit = cells.join(F.broadcast(queries), inside(columns))
    summed = hit.groupBy("qid").agg(F.sum(value).alias(out))
    return queries.select("qid").join(summed, "qid", "left").withColumn(out, F.coalesce(F.col(out), F.lit(0)))


def truth(queries: DataFrame, df: DataFrame, fixture: Fixture) -> DataFrame:
    """(qid, truth): exact counts."""
    return over_cells(queries, df.groupBy(*fixture.columns).agg(F.count("*").alias("n")), fixture.columns, "n", "truth")


def without_empty(queries: DataFrame, answers: DataFrame) -> DataFrame:
    """Queries whose true answer at the start isn't zero."""
    return queries.join(answers.where("truth > 0").select("qid"), "qid", "left_semi")


def aqp_queries(df: DataFrame, category: str, number: str, n: int = QUERIES, seed: int = 1, width: float = 0.3) -> DataFrame:
    """(qid, category code, lo, hi): a range of random width around an anchor row, and its category."""
    lo, hi = df.agg(F.min(number), F.max(number)).first()
    a = anchors(df, n, seed)
    w = F.lit(width * (hi - lo)) * _unit("width", seed) / F.lit(float(HASH_SPACE))
    return a.select("qid", category, F.round(F.col(number) - w, 4).alias("lo"), F.round(F.col(number) + w, 4).alias("hi"))


def aqp_truth(queries: DataFrame, df: DataFrame, category: str, number: str, target: str | None = None) -> DataFrame:
    """(qid, count, sum, avg).

    The bounds of a category's queries cut the axis into pieces: the bounds themselves and the gaps
    between them.  A row finds its piece by halving and is added up there; queries then sum pieces.
    So a row is read once, however many queries there are.  The workload (some thousand queries) is
    broadcast.
    """
    t = F.col(target or number)
    queries = queries.withColumns({c: zero(F.col(c)) for c in ("lo", "hi")})
    ends = queries.select(category, F.explode(F.array("lo", "hi")).alias("__e")).where(F.col("__e").isNotNull())
    bounds = ends.groupBy(category).agg(F.array_sort(F.collect_set("__e")).alias("__ends"))
    most = bounds.agg(F.coalesce(F.max(F.size("__ends")), F.lit(0))).first()[0]
    bounds = F.broadcast(bounds)
    found = df.select(F.col(category), F.col(number).alias("__v"), t.alias("__t")).join(bounds, category)
    at = found.withColumn("__at", position(F.col("__ends"), most, F.col("__v")))
    piece = 2 * F.col("__at") - F.when(F.get("__ends", F.col("__at") - 1) == F.col("__v"), 1).otherwise(0)
    sums = at.where("__v is not null").groupBy(category, piece.alias("__piece")).agg(F.count("*").alias("__n"), F.sum("__t").alias("__s"))
    edge = lambda c: 2 * F.array_position("__ends", F.col(c)) - 1
    asked = queries.join(bounds, category).select("qid", category, edge("lo").alias("__lo"), edge("hi").alias("__hi"))
    hit = sums.join(F.broadcast(asked), category).where(F.col("__piece").between(F.col("__lo"), F.col("__hi")))
    summed = hit.groupBy("qid").agg(F.sum("__n").alias("count"), F.sum("__s").alias("sum"))
    out = queries.select("qid").join(summed, "qid", "left").fillna(0, ["count"]).fillna(0.0, ["sum"])
    return out.withColumn("avg", F.try_divide("sum", "count"))


def truth_added(before: DataFrame, of_batch: DataFrame) -> DataFrame:
    """Counts after an insertion: the old answers plus the batch's."""
    b = of_batch.select("qid", F.col("truth").alias("__b"))
    return before.join(b, "qid").select("qid", (F.col("truth") + F.col("__b")).alias("truth"))


def toy_mixture(spark, seed: int = 1, per_category: int = 1000, means: tuple[float, ...] = (-0.8, -0.4, 0.0, 0.4, 0.8), std: float = 0.05, categories: int = 10) -> DataFrame:
    """(rk, x, y): ``categories`` codes with draws from an even mixture of normals (Box-Muller on hashes)."""
    rows = spark.range(categories * per_category).select(F.concat(F.lit(f"{seed}|"), F.col("id")).alias("rk"), F.floor(F.col("id") / per_category).cast("int").alias("x"))
    u = lambda what: (row_hash("rk", f"{what}{seed}") + F.lit(0.5)) / F.lit(float(HASH_SPACE))
    z = F.sqrt(-2 * F.log(u("r"))) * F.cos(2 * F.pi() * u("a"))
    m = F.element_at(F.array(*[F.lit(v) for v in means]), (row_hash("rk", f"m{seed}") % len(means) + 1).cast("int"))
    return rows.select("rk", "x", (m + F.lit(std) * z).alias("y"))
