"""Column expressions that stay inside whole-stage code generation."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

HASH_SPACE = 1 << 32


def row_hash(key: Column | str, seed: int | str = 0) -> Column:
    """A reproducible number in [0, 2^32) from a row's key: the first eight hexadecimal digits of an MD5."""
    key = F.col(key) if isinstance(key, str) else key
    return F.conv(F.substring(F.md5(F.concat_ws("|", key, F.lit(str(seed)))), 1, 8), 16, 10).cast("long")


def cut(fraction: float) -> int:
    """Hashes below this number are the given share of the hash space."""
    return int(fraction * HASH_SPACE)


def hash_sample(df: DataFrame, fraction: float, seed: int | str, key: str = "rk") -> DataFrame:
    """The same rows on every run and for every partitioning; larger fractions contain smaller ones."""
    return df.where(row_hash(key, seed) < F.lit(cut(fraction)))


def zero(c: Column) -> Column:
    """Turns -0.0 into 0.0 before a value is grouped, hashed or printed."""
    return c + F.lit(0.0)


def scale(c: Column, lo: float, hi: float) -> Column:
    """Maps [lo, hi] to [-1, 1]."""
    return F.lit(2.0) * (c - F.lit(lo)) / F.lit(hi - lo) - F.lit(1.0)


def band(c: Column, edges: list[float]) -> Column:
    """Index of the interval between sorted edges that holds the value."""
    out = F.lit(len(edges))
    for i in reversed(range(len(edges))):
        out = F.when(c < F.lit(edges[i]), F.lit(i)).otherwise(out)
    return out


def position(values: Column, n: int, x: Column) -> Column:
    """How many of the ``n`` (or fewer) entries of a sorted array are at most ``x``, by halving: log2(n) steps, all in generated code."""
    at = F.lit(0)
    for k in reversed(range(max(1, n).bit_length())):
        at = at + F.when(F.get(values, at + F.lit((1 << k) - 1)) <= x, F.lit(1 << k)).otherwise(F.lit(0))
    return at


def normal_cdf(z: Column) -> Column:
    """Standard normal distribution function by a rational approximation, absolute error below 7.5e-8.

    Constants are fixed values of the published approximation.
    """
    b = (0.319381530, -0.356563782, 1.781477937, -1.821255978, 1.330274429)
    a = F.abs(z)
    t = F.lit(1.0) / (F.lit(1.0) + F.lit(0.2316419) * a)
    poly = F.lit(b[4])
    for x in reversed(b[:4]):
        poly = F.lit(x) + t * poly
    tail = F.exp(-a * a / 2.0) / F.lit(math.sqrt(2 * math.pi)) * t * poly
    return F.when(z >= 0, F.lit(1.0) - tail).otherwise(tail)


def normal_pdf(z: Column) -> Column:
    return F.exp(-z * z / 2.0) / F.lit(math.sqrt(2 * math.pi))


def log_sum_exp(z: Column) -> Column:
    top = F.array_max(z)
    return top + F.log(F.aggregate(z, F.lit(0.0), lambda a, x: a + F.exp(x - top)))


def soft_cross_entropy(teacher: Column, student: Column, temperature: float | Column) -> Column:
    """Cross-entropy of the student's tempered distribution under the teacher's; both are arrays of logits."""
    t = F.transform(teacher, lambda x: x / F.lit(temperature))
    s = F.transform(student, lambda x: x / F.lit(temperature))
    lt, ls = log_sum_exp(t), log_sum_exp(s)
    terms = F.zip_with(t, s, lambda x, y: -F.exp(x - lt) * (y - ls))
    return F.aggregate(terms, F.lit(0.0), lambda a, x: a + x)


def squared_logit_gap(teacher: Column, student: Column) -> Column:
    """Sum of squared differences of two arrays of logits."""
    return F.aggregate(F.zip_with(teacher, student, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda a, x: a + x)


def mixture_pdf(y: Column, omega: Column, mu: Column, sigma: Column) -> Column:
    parts = F.transform(F.arrays_zip(omega.alias("w"), mu.alias("m"), sigma.alias("s")), lambda p: p["w"] / p["s"] * normal_pdf((y - p["m"]) / p["s"]))
    return F.aggregate(parts, F.lit(0.0), lambda a, x: a + x)


def mixture_mass(lo: Column, hi: Column, omega: Column, mu: Column, sigma: Column) -> Column:
    """Probability of [lo, hi]."""
    parts = F.transform(F.arrays_zip(omega.alias("w"), mu.alias("m"), sigma.alias("s")), lambda p: p["w"] * (normal_cdf((hi - p["m"]) / p["s"]) - normal_cdf((lo - p["m"]) / p["s"])))
    return F.aggregate(parts, F.lit(0.0), lambda a, x: a + x)


def mixture_first_moment(lo: Column, hi: Column, omega: Column, mu: Column, sigma: Column) -> Column:
    """Integral of y times the density over [lo, hi], from the truncated normal's mean."""

    def part(p: Column) -> Column:
        a, b = (lo - p["m"]) / p["s"], (hi - p["m"]) / p["s"]
        return p["w"] * (p["m"] * (normal_cdf(b) - normal_cdf(a)) - p["s"] * (normal_pdf(b) - normal_pdf(a)))

    return F.aggregate(F.transform(F.arrays_zip(omega.alias("w"), mu.alias("m"), sigma.alias("s")), part), F.lit(0.0), lambda a, x: a + x)


def q_error(estimate: Column, truth: Column) -> Column:
    """Larger over smaller of estimate and truth, both at least 1."""
    e, t = F.greatest(estimate.cast("double"), F.lit(1.0)), F.greatest(truth.cast("double"), F.lit(1.0))
    return F.greatest(e, t) / F.least(e, t)


def relative_error(estimate: Column, truth: Column) -> Column:
    """Percent; null where the truth is 0."""
    return F.abs(estimate - truth) / F.nullif(F.abs(truth), F.lit(0.0)) * 100
