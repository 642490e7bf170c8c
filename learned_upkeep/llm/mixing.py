"""Operator 7, mixing sources to target weights (DataFrame functions only).

Word counts are summed per source (partial sums, so a hot source costs nothing), the summed table
gives each source its target and repetition rate, and a document is emitted floor(rate) times plus
one hash-seeded Bernoulli copy with probability rate - floor(rate).  Of ``seeds`` hash seeds each
source uses the one whose draw comes nearest to its target; all of them are summed in one pass.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import BROADCAST_ROWS, WORD, materialise, replicated, salted, whole_text

WEIGHTS = (5, 2, 1)
SHARE = 1.5
CEILING = 2.0
SEEDS = 16


def sizes(docs: DataFrame) -> DataFrame:
    """(doc_id, source, size): words of the whole text, 0 for null."""
    return docs.select("doc_id", "source", F.regexp_count(whole_text(), F.lit(WORD)).cast("long").alias("size"))


def source_targets(sized: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, ceiling: float = CEILING) -> DataFrame:
    """(source, source_size, target): weighted shares of ``share`` times all words, none above ``ceiling`` times its source.

    Resharing the excess by weight ends where target = min(ceiling * size, weight * level) for one
    common level.  Sorted by ceiling * size / weight, the stopped sources form a prefix; the
    level follows from the first prefix that leaves every later source below its stop.
    """
    # summing starts in the map tasks, so this table has one row for each source
    sums = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    one = W.partitionBy(F.lit(0))
    nth = F.pmod(F.row_number().over(one.orderBy(F.col("source").asc_nulls_last())) - 1, F.lit(len(weights)))
    by_stop = one.orderBy("__stop", F.col("source").asc_nulls_last())
    upto = by_stop.rowsBetween(W.unboundedPreceding, -1)
    table = (
        sums.withColumn("__w", F.element_at(F.array(*[F.lit(float(w)) for w in weights]), nth + 1))
        .withColumn("__most", F.lit(ceiling) * F.col("source_size"))
        .withColumn("__stop", F.col("__most") / F.col("__w"))
        .withColumn("__budget", F.sum("source_size").over(one) * F.lit(float(min(share, ceiling))))
        .withColumn("__level", (F.col("__budget") - F.coalesce(F.sum("__most").over(upto), F.lit(0.0))) / (F.sum("__w").over(one) - F.coalesce(F.sum("__w").over(upto), F.lit(0.0))))
    )
    # the level is right at the first source that its own level does not stop
    level = F.min_by(F.when(F.col("__level") < F.col("__stop"), F.col("__level")), F.when(F.col("__level") < F.col("__stop"), F.col("__stop"))).over(one)
    return table.withColumn("__l", level).select(
        "source", "source_size", F.when(F.col("__l").isNull(), F.col("__most")).otherwise(F.least("__most", F.col("__w") * F.col("__l"))).alias("target")
    )


def _draw(seed: Column | int) -> Column:
    """Uniform in [0, 1) from the seed and the document; equal for repeated rows."""
    seed = F.lit(seed) if isinstance(seed, int) else seed
    return F.shiftrightunsigned(F.xxhash64(seed, F.col("doc_id"), F.col("size")), 11) / F.lit(float(1 << 53))


def rates(sized: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, ceiling: float = CEILING, seeds: int = SEEDS) -> DataFrame:
    """(source, source_size, target, rate, seed): one row for each source."""
    rated = source_targets(sized, weights, share, ceiling).withColumn("rate", F.coalesce(F.try_divide(F.col("target"), F.col("source_size")), F.lit(0.0)))
    rated = materialise(rated, "rates")
    whole, part = F.floor("rate"), F.col("rate") - F.floor("rate")
    drawn = _with_rates(sized, rated).groupBy("source").agg(*[F.sum(F.when(_draw(s) < part, F.col("size")).otherwise(0)).alias(f"__s{s}") for s in range(seeds)])
    best = F.array_min(F.array(*[F.struct(F.abs(F.col(f"__s{s}") + whole * F.col("source_size") - F.col("target")).alias("miss"), F.lit(s).alias("seed")) for s in range(seeds)]))["seed"]
    chosen = rated.join(drawn.withColumnRenamed("source", "__src"), F.col("source").eqNullSafe(F.col("__src")))
    return materialise(chosen.select(*rated.columns, best.alias("seed")), "seeds")


def with_copies(sized: DataFrame, chosen: DataFrame) -> DataFrame:
    """Adds source_size, target and copies to rows that carry doc_id, source and size."""
    n = F.floor("rate") + F.when(_draw(F.col("seed")) < F.col("rate") - F.floor("rate"), 1).otherwise(0)
    return _with_rates(sized, chosen).withColumn("copies", n.cast("long"))


def copies(docs: DataFrame, **options) -> DataFrame:
    """(doc_id, source, size, source_size, target, copies, taken) of every row.

    A null text has no words; a null source is a source of its own, ordered last.  A source without
    words has target 0 and its documents are not taken.  Repeated rows share their draw.  An empty
    table gives an empty result; further columns are ignored.  The draw depends on the seed, doc_id
    and size alone, so reruns agree.
    """
    sized = materialise(sizes(docs), "sizes")
    out = with_copies(sized, rates(sized, **options))
    return out.select("doc_id", "source", "size", "source_size", "target", "copies", (F.col("size") * F.col("copies")).alias("taken"))


def mix(docs: DataFrame, **options) -> DataFrame:
    """The rows of ``docs``, each as often as the mix takes it (0, 1 or 2 times), with their own columns.

    Only the table of sources is joined to the documents, so their texts are not shuffled.
    """
    chosen = rates(materialise(sizes(docs), "sizes"), **options)
    own = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("__row"), "doc_id", "source", F.regexp_count(whole_text(), F.lit(WORD)).cast("long").alias("size"))
    taken = with_copies(own, chosen).where("copies > 0").withColumn("__copy", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int"))))
    return taken.select("__row.*")


def _with_rates(sized: DataFrame, rates: DataFrame) -> DataFrame:
    """Joins the table of sources: broadcast if it is small enough, else salted by document."""
    if rates.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS:
        r = rates.withColumnRenamed("source", "__src")
        return sized.join(F.broadcast(r), F.col("source").eqNullSafe(F.col("__src"))).drop("__src")
    r = replicated(rates).withColumnsRenamed({"source": "__src", "__salt": "__salt2"})
    return salted(sized, "doc_id").join(r, F.col("source").eqNullSafe(F.col("__src")) & (F.col("__salt") == F.col("__salt2"))).drop("__src", "__salt", "__salt2")
