"""The two-sample test on mean losses: offline bootstrap, online comparison.

A loss is always "lower is better" and the shift is new minus old.  The default tail is two-sided.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from statistics import NormalDist

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.columns import HASH_SPACE, normal_cdf, row_hash

BOOTSTRAPS = 1000
FACTOR = 2.0
OLD_FRACTION, NEW_FRACTION = 0.01, 0.1
LEAST_ROWS = 100


def moments(scored: DataFrame, prefix: str) -> DataFrame:
    return scored.agg(F.avg("loss").alias(f"{prefix}_mean"), F.stddev_pop("loss").alias(f"{prefix}_std"), F.count("*").alias(f"{prefix}_n"))


def mean_shift(old: DataFrame, new: DataFrame) -> DataFrame:
    """One row: both means, sizes and the shift (new minus old)."""
    both = moments(old, "old").crossJoin(moments(new, "new"))  # one row each
    return both.select("old_mean", "new_mean", "old_n", "new_n", (F.col("new_mean") - F.col("old_mean")).alias("shift"))


def normal_std(scored: DataFrame, rows: int) -> DataFrame:
    """Standard deviation of the mean of ``rows`` losses under the normal limit."""
    return scored.agg((F.stddev_pop("loss") / math.sqrt(rows)).alias("std"), F.avg("loss").alias("mean"))


def poisson_weight(u: Column, rate: float = 1.0) -> Column:
    """A Poisson number from a uniform one by its distribution function (up to 8, beyond which 1e-6 of the mass lies at rate 1)."""
    out, term, total = F.lit(9), math.exp(-rate), 0.0
    bounds = []
    for k in range(9):
        total += term
        bounds.append((total, k))
        term *= rate / (k + 1)
    for bound, k in reversed(bounds):
        out = F.when(u < F.lit(bound), F.lit(k)).otherwise(out)
    return out


def bootstrap_poisson(scored: DataFrame, iterations: int, seed: int = 1, rate: float = 1.0) -> DataFrame:
    """(boot_id, mean_loss) in one pass: each row takes part in each resample a Poisson number of times."""
    each = scored.select("loss", "rk", F.explode(F.sequence(F.lit(0), F.lit(iterations - 1))).alias("boot_id"))
    u = row_hash(F.concat_ws("|", "rk", "boot_id"), f"boot{seed}") / F.lit(float(HASH_SPACE))
    w = each.select("boot_id", "loss", poisson_weight(u, rate).alias("w"))
    return w.groupBy("boot_id").agg((F.sum(F.col("w") * F.col("loss")) / F.sum("w")).alias("mean_loss"))


def bootstrap_cells(counted: DataFrame, iterations: int = BOOTSTRAPS, seed: int = 1) -> DataFrame:
    """(boot_id, mean_loss) over all rows, from (loss, n) of each cell: rows of one loss take part a Poisson number of times whose mean is their count."""
    import pandas as pd

    table = counted.select("loss", "n").orderBy("loss", "n").toPandas()  # at most the joint domain
    spark = counted.sparkSession
    shared = spark.sparkContext.broadcast((table["loss"].to_numpy("float64"), table["n"].to_numpy("float64")))

    def run(frames):
        loss, n = shared.value
        for ids in frames:
            w = [np.random.default_rng([seed, int(i)]).poisson(n) for i in ids["id"]]
            yield pd.DataFrame({"boot_id": ids["id"].astype("int32"), "mean_loss": [float(x @ loss / x.sum()) if x.sum() else None for x in w]})

    return spark.range(iterations).mapInPandas(run, "boot_id int, mean_loss double")


def bootstrap_binned(scored: DataFrame, iterations: int = BOOTSTRAPS, rows: int | None = None, bins: int = 4096, seed: int = 1) -> np.ndarray:
    """Means of ``rows`` losses drawn with replacement, from a histogram of at most ``bins`` + 1 rows.

    The rows are aggregated once; the draws are multinomial counts of bins on the driver, so neither
    the number of old rows nor the number of iterations touches the data again.
    """
    lo, hi, n = scored.agg(F.min("loss"), F.max("loss"), F.count("*")).first()
    if not n:
        raise ValueError("no old rows to bootstrap")
    width = (hi - lo) / bins or 1.0
    table = scored.groupBy(F.floor((F.col("loss") - F.lit(lo)) / F.lit(width)).alias("b")).agg(F.count("*").alias("n"), F.avg("loss").alias("m")).orderBy("b").toPandas()
    p, m = table["n"].to_numpy("float64") / n, table["m"].to_numpy("float64")
    draws = np.random.default_rng(seed).multinomial(rows or n, p, size=iterations)
    return draws @ m / (rows or n)


@dataclass(frozen=True)
class Baseline:
    """What the offline phase leaves for the online test."""

    mean: float
    std: float
    n_boot: int
    sigma: float
    n_old: int
    means: tuple[float, ...] = ()


def offline(scored: DataFrame, iterations: int = BOOTSTRAPS, rows: int | None = None, seed: int = 1) -> Baseline:
    """``rows`` defaults to 1 % of the old rows, at least 100."""
    n, sigma = scored.agg(F.count("*"), F.coalesce(F.stddev_pop("loss"), F.lit(0.0))).first()
    rows = rows or max(LEAST_ROWS, int(OLD_FRACTION * n))
    means = bootstrap_binned(scored, iterations, rows, seed=seed)
    return Baseline(float(means.mean()), float(means.std(ddof=1)), rows, float(sigma), n, tuple(np.sort(means)))


def offline_counted(loss: np.ndarray, n: np.ndarray, iterations: int = BOOTSTRAPS, seed: int = 1) -> Baseline:
    """:func:`offline` from the losses of cells and the counts of their rows; draws are multinomial counts of cells."""
    total, met = int(n.sum()), n > 0
    if not total:
        raise ValueError("no old rows to bootstrap")
    mean = np.average(loss, weights=n)
    rows = max(LEAST_ROWS, int(OLD_FRACTION * total))
    means = np.random.default_rng(seed).multinomial(rows, n[met] / total, size=iterations) @ loss[met] / rows
    return Baseline(float(means.mean()), float(means.std(ddof=1)), rows, float(np.sqrt(np.average((loss - mean) ** 2, weights=n))), total, tuple(np.sort(means)))


def factor(delta: float | None, tail: str = "two_sided") -> float:
    """The number of standard deviations for a significance level; the published 2 without one."""
    if delta is None:
        return FACTOR
    return NormalDist().inv_cdf(1 - delta / (2 if tail == "two_sided" else 1))


def threshold(base: Baseline, n_new: int, mode: str = "fixed", k: float = FACTOR) -> float:
    """``fixed``: k bootstrap deviations.  ``size_matched``: scaled to the batch's size.  ``pooled``: from both sizes."""
    floor = 1e-9 * max(1.0, abs(base.mean))
    std = {
        "fixed": base.std,
        "size_matched": base.std * math.sqrt(base.n_boot / max(1, n_new)),
        "pooled": base.sigma * math.sqrt(1 / max(1, base.n_old) + 1 / max(1, n_new)),
    }[mode]
    return k * max(std, floor)


@dataclass(frozen=True)
class Verdict:
    shift: float
    threshold: float
    z: float
    p_normal: float
    p_empirical: float
    is_ood: bool
    n_old: int
    n_new: int


def fires(shift, limit, tail: str = "two_sided"):
    if tail == "two_sided":
        return abs(shift) > limit
    return shift > limit if tail == "upper" else -shift > limit


def p_value(shift: float, base: Baseline, tail: str = "two_sided") -> tuple[float, float]:
    """(normal, empirical): the chance of a shift at least as large without drift."""
    z = shift / max(base.std, 1e-9 * max(1.0, abs(base.mean)))
    upper = 1 - NormalDist().cdf(z)
    normal = {"two_sided": 2 * min(upper, 1 - upper), "upper": upper, "lower": 1 - upper}[tail]
    d = np.asarray(base.means) - base.mean
    hits = {"two_sided": np.abs(d) >= abs(shift), "upper": d >= shift, "lower": d <= shift}[tail]
    return float(normal), float((hits.sum() + 1) / (d.size + 1))


def test_batch(scored_batch: DataFrame, base: Baseline, mode: str = "fixed", tail: str = "two_sided", k: float = FACTOR) -> Verdict:
    """One pass over the scored sample of the batch.  Fewer than two rows, or a loss that isn't a number, give no drift signal but an error."""
    n, mean = scored_batch.agg(F.count("*"), F.avg("loss")).first()
    return _verdict(n, mean, base, mode, tail, k)


def test_counted(loss: np.ndarray, n: np.ndarray, base: Baseline, mode: str = "fixed", tail: str = "two_sided", k: float = FACTOR) -> Verdict:
    """:func:`test_batch` from the losses of cells and the counts of the batch's rows."""
    return _verdict(int(n.sum()), float(np.average(loss, weights=n)) if n.sum() else None, base, mode, tail, k)


def _verdict(n: int, mean: float | None, base: Baseline, mode: str, tail: str, k: float) -> Verdict:
    if n < 2 or mean is None or math.isnan(mean):
        raise ValueError(f"a batch of {n} rows with mean loss {mean} can't be tested")
    shift = mean - base.mean
    limit = threshold(base, n, mode, k)
    normal, empirical = p_value(shift, base, tail)
    return Verdict(shift, limit, shift / (limit / k), normal, empirical, bool(fires(shift, limit, tail)), base.n_old, n)


def by_column(old: DataFrame, new: DataFrame, columns: tuple[str, ...], k: float = FACTOR) -> DataFrame:
    """(position, column, old_loss, new_loss, shift, threshold, is_ood) from l1 … lm of both sides.

    The joint loss is the sum over columns.  The loss of a column given those before it moves with
    its conditional distribution; that of the columns before it moves with their own distribution.
    """
    names = [f"l{i + 1}" for i in range(len(columns))]
    means = lambda df, p: df.agg(*[F.avg(c).alias(f"{p}{c}") for c in names], *[F.stddev_pop(c).alias(f"{p}s{c}") for c in names], F.count("*").alias(f"{p}n"))
    both = means(old, "o").crossJoin(means(new, "n"))  # one row each
    limit = lambda c: k * F.greatest(F.col(f"os{c}"), F.lit(1e-9)) * F.sqrt(1 / F.col("on") + 1 / F.col("nn"))
    each = [F.struct(F.lit(i).alias("position"), F.lit(columns[i]).alias("column"), F.col(f"o{c}").alias("old_loss"), F.col(f"n{c}").alias("new_loss"), (F.col(f"n{c}") - F.col(f"o{c}")).alias("shift"), limit(c).alias("threshold")) for i, c in enumerate(names)]
    return both.select(F.explode(F.array(*each)).alias("e")).select("e.*").withColumn("is_ood", F.abs("shift") > F.col("threshold"))


def two_sample(old: DataFrame, new: DataFrame, n_boot: int, k: float = FACTOR) -> DataFrame:
    """The same test as one lazy row, with the normal limit instead of the bootstrap: no driver round trip."""
    both = moments(old, "old").crossJoin(moments(new, "new"))
    std = F.greatest(F.col("old_std") / math.sqrt(n_boot), F.lit(1e-9))
    shift = F.col("new_mean") - F.col("old_mean")
    return both.select(
        "old_mean", "new_mean", "old_n", "new_n", shift.alias("shift"), (k * std).alias("threshold"), (shift / std).alias("z"),
        (2 * (1 - normal_cdf(F.abs(shift / std)))).alias("p"), (F.abs(shift) > k * std).alias("is_ood"),
    )


def detector_batches(pool: DataFrame, batches: int, size: int, seed: int = 1) -> DataFrame:
    """(batch_no, pos, …): ``batches`` draws of ``size`` rows each from a scored pool, all in one job.

    A draw is the pool's rows with the smallest hash of (row, batch), found by a threshold a little
    above the wanted share and then numbered; each batch is its own small group.
    """
    from pyspark.sql import Window as W

    n = pool.count()
    share = min(1.0, 1.3 * size / max(1, n) + 20 / max(1, n))
    each = pool.select("rk", "loss", F.explode(F.sequence(F.lit(0), F.lit(batches - 1))).alias("batch_no"))
    h = row_hash(F.concat_ws("|", "rk", "batch_no"), f"draw{seed}")
    near = each.withColumn("h", h).where(F.col("h") < F.lit(int(share * HASH_SPACE)))
    return near.withColumn("pos", F.row_number().over(W.partitionBy("batch_no").orderBy("h", "rk"))).where(F.col("pos") <= size).drop("h")


def pool_batches(pool: DataFrame, batches: int, sizes: tuple[int, ...], seed: int = 1) -> DataFrame:
    """(level, batch_no, size, n, l): mean losses of ``batches`` draws without replacement from a pool with ``level`` and ``loss``.

    Level 0 draws from the whole pool, further levels from their slice.  A size is a prefix of the batch's
    draw, and n is less than it where the slice is smaller.  The pool is counted once by loss (one
    row for each cell and level), and draws are positions in the running counts.
    """
    import pandas as pd

    table = pool.groupBy("level", "loss").agg(F.count("*").alias("n")).orderBy("level", "loss").toPandas()
    slices = [(0, table), *[(int(k), t) for k, t in table.groupby("level") if k]]
    shared = pool.sparkSession.sparkContext.broadcast([(k, t["loss"].to_numpy(), np.cumsum(t["n"].to_numpy())) for k, t in slices])

    def run(frames):
        for ids in frames:
            out = []
            for i in ids["id"]:
                level, loss, upto = shared.value[i // batches]
                at = np.random.default_rng([seed, int(i)]).choice(upto[-1], min(max(sizes), upto[-1]), replace=False)
                total = np.cumsum(loss[np.searchsorted(upto, at, side="right")])
                out += [(level, i % batches, k, min(k, at.size), total[min(k, at.size) - 1] / min(k, at.size)) for k in sizes]
            yield pd.DataFrame(out, columns=["level", "batch_no", "size", "n", "l"])

    return pool.sparkSession.range(len(slices) * batches).mapInPandas(run, "level int, batch_no long, size int, n long, l double")


def batch_verdicts(drawn: DataFrame, mean: float, limit: float) -> DataFrame:
    """(batch_no, n, shift, fired)."""
    b = drawn.groupBy("batch_no").agg(F.count("*").alias("n"), (F.avg("loss") - F.lit(mean)).alias("shift"))
    return b.withColumn("fired", F.abs("shift") > F.lit(limit))
