"""Query answers and synthetic rows from learned models."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.columns import mixture_first_moment, mixture_mass, scale
from ..nn.darn import MaskedAutoregressive
from ..nn.mdn import MixtureDensity
from ..nn.training import Params
from ..nn.vae import TabularVae


def mixture_table(spark: SparkSession, model: MixtureDensity, params: Params, category: str) -> DataFrame:
    """The whole mixture model as one row for each category: (category, omega, mu, sigma)."""
    return spark.createDataFrame(model.table(params), f"{category} int, omega array<double>, mu array<double>, sigma array<double>")


def aqp(queries: DataFrame, mixtures: DataFrame, frequencies: DataFrame, category: str, lo: float, hi: float) -> DataFrame:
    """(qid, count, sum, avg) of range queries (qid, category, lo, hi) from mixtures over [lo, hi] scaled to [-1, 1].

    COUNT is the category's frequency times the range's probability; SUM uses the truncated means.
    Queries meet two tables with a row for each category, so this is a broadcast join of any number of queries.
    """
    m = mixtures.join(frequencies, category, "left")
    q = queries.join(F.broadcast(m), category)
    a, b = scale(F.col("lo"), lo, hi), scale(F.col("hi"), lo, hi)
    parts = (F.col("omega"), F.col("mu"), F.col("sigma"))
    q = q.withColumn("__m", F.greatest(mixture_mass(a, b, *parts), F.lit(0.0))).withColumn("__f", mixture_first_moment(a, b, *parts))
    n = F.coalesce(F.col("n"), F.lit(0))
    back = F.lit((hi - lo) / 2)
    total = n * (back * (F.col("__f") + F.col("__m")) + F.lit(lo) * F.col("__m"))
    out = q.select("qid", (n * F.col("__m")).alias("count"), total.alias("sum"))
    return out.withColumn("avg", F.when(F.col("count") > 1e-9, F.col("sum") / F.col("count")))


def aqp_other_target(queries: DataFrame, mixtures: DataFrame, frequencies: DataFrame, second: MixtureDensity, second_params: Params, category: str, lo: float, hi: float, cells: int = 64) -> DataFrame:
    """SUM and AVG of another column: its conditional mean given the range column's cell, integrated over ``cells`` cells.

    ``second`` is a mixture model whose input code is category * cells + cell.
    """
    spark = queries.sparkSession
    means = [(i // cells, i % cells, float(np.dot(w, m))) for i, w, m, _ in second.table(second_params)]
    mean_table = spark.createDataFrame(means, f"{category} int, cell int, cond_mean double")
    width = (hi - lo) / cells
    cut = queries.withColumn("cell", F.explode(F.sequence(F.lit(0), F.lit(cells - 1))))
    cut = cut.withColumn("lo", F.greatest("lo", F.lit(lo) + F.col("cell") * width)).withColumn("hi", F.least("hi", F.lit(lo) + (F.col("cell") + 1) * width)).where("lo < hi")
    mass = aqp(cut.withColumn("qid", F.struct("qid", "cell")), mixtures, frequencies, category, lo, hi).select("qid.qid", "qid.cell", "count")
    joined = mass.join(cut.select("qid", "cell", category), ["qid", "cell"]).join(F.broadcast(mean_table), [category, "cell"])
    return joined.groupBy("qid").agg(F.sum("count").alias("count"), F.sum(F.col("count") * F.col("cond_mean")).alias("sum"))


def estimate_counts(queries: DataFrame, model: MaskedAutoregressive, params: Params, columns: tuple[str, ...], rows: int, paths: int = 500, seed: int = 1) -> DataFrame:
    """(qid, estimate) of box queries by progressive sampling; queries are spread over tasks and weights are broadcast.

    Draws depend on the query's number and the seed, not on how queries are partitioned.
    """
    shared = queries.sparkSession.sparkContext.broadcast(params)
    names = [f"{c}_{e}" for c in columns for e in ("lo", "hi")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            box = np.column_stack([b.column(n).to_numpy() for n in names]).astype(int).reshape(b.num_rows, len(columns), 2)
            qid = b.column("qid").to_pylist()
            out = [rows * model.box_mass(shared.value, x[:, 0], x[:, 1], paths, np.random.default_rng((seed, q))) for q, x in zip(qid, box, strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(qid, pa.int64()), pa.array(out, pa.float64())], ["qid", "estimate"])

    return queries.select(F.col("qid").cast("long"), *names).repartition("qid").mapInArrow(run, "qid long, estimate double")


def cell_masses(grid: DataFrame, model: MaskedAutoregressive, params: Params, columns: tuple[str, ...]) -> DataFrame:
    """(columns, prob) of a small joint domain: exact answers by enumeration."""
    shared = grid.sparkSession.sparkContext.broadcast(params)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                p = model.cell_mass(shared.value, np.column_stack([b.column(c).to_numpy() for c in columns]))
                yield pa.RecordBatch.from_arrays([*[b.column(c) for c in columns], pa.array(p)], [*columns, "prob"])

    return grid.select(*columns).mapInArrow(run, ", ".join(f"{c} int" for c in columns) + ", prob double")


def generate(spark: SparkSession, n: int, model: TabularVae, params: Params, columns: tuple[str, ...], seed: int = 1, block: int = 10_000) -> DataFrame:
    """``n`` synthetic rows of codes.  Rows are made in numbered blocks, so a lost task makes the same rows again."""
    shared = spark.sparkContext.broadcast(params)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k in b.column("id").to_pylist():
                size = min(block, n - k * block)
                x = model.sample(shared.value, size, np.random.default_rng((seed, k))).astype("int32")
                yield pa.RecordBatch.from_arrays([pa.array(x[:, i]) for i in range(x.shape[1])], list(columns))

    return spark.range(-(-n // block)).mapInArrow(run, ", ".join(f"{c} int" for c in columns))


def judge(train: DataFrame, holdout: DataFrame, features: tuple[str, ...], target: str, trees: int = 20, seed: int = 1) -> float:
    """Micro-F1 on held-out real rows of a forest trained on the given (real or synthetic) rows."""
    from pyspark.ml.classification import RandomForestClassifier
    from pyspark.ml.feature import VectorAssembler

    from .metrics import micro_f1

    ready = lambda df: VectorAssembler(inputCols=list(features), outputCol="features").transform(df.select(*features, F.col(target).cast("double").alias("label")))
    model = RandomForestClassifier(numTrees=trees, maxDepth=8, seed=seed).fit(ready(train))
    return micro_f1(model.transform(ready(holdout)))
