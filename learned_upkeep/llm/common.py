"""Shared plumbing of the training-data operators: input columns, scratch tables, salted joins."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Java pattern of one word: a run of anything but ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"
#: Replicas of the small side in a salted join; one key of the large side is spread over so many tasks.
SALTS = 16
#: Row bound under which a table of at most 100-byte rows may be broadcast (about 5 MB).
BROADCAST_ROWS = 50_000
#: Bound for a broadcast of document numbers.
BROADCAST_IDS = 2_000_000

_own_scratch: dict[str, str] = {}


def scratch_dir(spark: SparkSession) -> str:
    """Folder for intermediate tables: spark.checkpoint.dir, else (local runs only) a temporary folder."""
    shared = spark.conf.get("spark.checkpoint.dir", None)
    if shared:
        return shared.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    app = spark.sparkContext.applicationId
    if app not in _own_scratch:
        _own_scratch[app] = tempfile.mkdtemp(prefix="upkeep-scratch-")
    return _own_scratch[app]


#: Paths of the scratch tables of the scopes that are open, the innermost last.
_scopes: list[list[str]] = []


def _remove(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


@contextmanager
def scratch_scope(spark: SparkSession) -> Iterator[None]:
    """Scratch tables written inside go when the scope ends; those marked ``keep`` pass to the scope around it."""
    _scopes.append([])
    try:
        yield
    finally:
        for path in _scopes.pop():
            _remove(spark, path)


def materialise(df: DataFrame, name: str = "t", keep: bool = False, **options: str) -> DataFrame:
    """Write ``df`` once to the shared scratch folder and read it back, which cuts its lineage.

    The files survive lost executors.  They are removed with the scope (:func:`scratch_scope`), or
    when the driver's JVM ends.  ``keep`` marks a table that outlives the innermost scope.
    """
    spark = df.sparkSession
    path = f"{scratch_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.options(**options).parquet(path)
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(at)
    if len(_scopes) > keep:
        _scopes[-1 - keep].append(path)
    return spark.read.schema(df.schema).parquet(path)


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def whole_text(col: str = "text") -> Column:
    """The text itself; null counts as empty."""
    return F.coalesce(F.col(col), F.lit(""))


def without_ids(docs: DataFrame, dropped: DataFrame) -> DataFrame:
    """Rows of ``docs`` whose doc_id isn't among the ids of ``dropped`` (a written table with the one column __id).

    Up to BROADCAST_IDS ids (some 32 bytes each) are broadcast, so the texts stay where they are; beyond, both sides are shuffled.
    """
    ids = F.broadcast(dropped) if dropped.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS else dropped.hint("merge")
    return docs.join(ids, F.col("doc_id").eqNullSafe(F.col("__id")), "left_anti")


def replicated(df: DataFrame, salts: int = SALTS) -> DataFrame:
    """Every row once per salt, for the small side of a salted join."""
    return df.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))


def salted(df: DataFrame, *spread_by: str, salts: int = SALTS) -> DataFrame:
    """A salt from columns that differ between the rows of a hot key, for the large side."""
    return df.withColumn("__salt", F.pmod(F.xxhash64(*spread_by), F.lit(salts)).cast("int"))


def with_running_total(df: DataFrame, order_hash: str, value: str, out: str, keys: list[str], buckets: int = 512) -> DataFrame:
    """Exclusive running total of ``value`` by (``order_hash``, doc_id) within ``keys``, without one task per key.

    Rows are cut into ``buckets`` ranges of the hash; only bucket sums meet in one window
    (``buckets`` rows a key), and rows are ordered within their own bucket.
    """
    from pyspark.sql import Window as W

    cut = df.withColumn("__bucket", F.floor((F.col(order_hash) / F.lit(2.0**64) + 0.5) * buckets).cast("int"))
    sums = cut.groupBy(*keys, "__bucket").agg(F.sum(value).alias("__sum"))
    before = sums.select(
        *keys, "__bucket",
        F.coalesce(F.sum("__sum").over(W.partitionBy(*keys, F.lit(0)).orderBy("__bucket").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("__before"),
    )
    inside = W.partitionBy(*keys, "__bucket").orderBy(order_hash, "doc_id").rowsBetween(W.unboundedPreceding, -1)
    return (
        cut.withColumn("__inside", F.coalesce(F.sum(value).over(inside), F.lit(0)))
        .join(before, [*keys, "__bucket"])
        .withColumn(out, F.col("__before") + F.col("__inside"))
        .drop("__before", "__inside", "__bucket")
    )
