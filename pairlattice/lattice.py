"""The lattice of attribute subsets and the triangular system between moments and pair counts."""

from __future__ import annotations

from math import comb

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def subsets(d: int, level: int) -> list[int]:
    """Bit masks of the subsets with ``level`` of ``d`` attributes, ascending."""
    return [m for m in range(1 << d) if m.bit_count() == level]


def masks(d: int, s: int) -> list[int]:
    return [m for k in range(s, d + 1) for m in subsets(d, k)]


def forward_moments(x: dict[int, float], n: float, d: int, s: int) -> dict[int, float]:
    """Moments of the levels from pair counts: self-pairs, and each j-similar pair once in every subset of its j common attributes."""
    return {k: comb(d, k) * n + sum(comb(j, k) * x.get(j, 0) for j in range(k, d + 1)) for k in range(s, d + 1)}


def invert_moments(y: dict[int, float], n: float, d: int, s: int) -> dict[int, float]:
    """Ordered pairs that agree on exactly k attributes, for k from d down to s."""
    return invert_sampled(y, {k: comb(d, k) * n for k in range(s, d + 1)}, d, s, 1.0)


def invert_sampled(y: dict[int, float], self_pairs: dict[int, float], d: int, s: int, ratio: float | dict = 1.0, clamp: str = "none") -> dict[int, float]:
    """The same from moments of samples; the result is on the scale of the population.

    Higher levels enter as they are in the population, so their scale is applied once.
    """
    r = ratio if isinstance(ratio, dict) else dict.fromkeys(range(s, d + 1), ratio)
    x: dict[int, float] = {}
    for k in range(d, s - 1, -1):
        x[k] = (y[k] - self_pairs[k]) / r[k] ** 2 - sum(comb(j, k) * x[j] for j in range(k + 1, d + 1))
        if clamp == "cascade":
            x[k] = max(0.0, x[k])
    return {k: max(0.0, v) for k, v in x.items()} if clamp == "final" else x


def invert_join(y: dict[int, float], d: int, s: int, ratio_a: float = 1.0, ratio_b: float = 1.0) -> dict[int, float]:
    """For two relations: no self-pairs; the chance that both sides are drawn is the product of the ratios."""
    return invert_sampled({k: v / (ratio_a * ratio_b) for k, v in y.items()}, dict.fromkeys(y, 0.0), d, s)


def printed_recursion(y: dict[int, float], n: float, d: int, s: int, r: float) -> dict[int, float]:
    """The recursion that scales higher levels twice when r < 1; kept to show its bias, not for use."""
    raw: dict[int, float] = {}
    for k in sorted(y, reverse=True):
        raw[k] = y[k] - r * comb(d, k) * n - r * r * sum(comb(j, k) * raw[j] for j in raw if j > k)
    return {k: v / (r * r) for k, v in raw.items()}


def inversion_matrix(d: int, s: int) -> list[tuple[int, int, int]]:
    """(k, j, coefficient): x_k is the sum over j >= k of coefficient * (y_j less self-pairs), the closed form of the system."""
    return [(k, j, (-1) ** (j - k) * comb(j, k)) for k in range(s, d + 1) for j in range(k, d + 1)]


def coefficients(spark: SparkSession, d: int, s: int) -> DataFrame:
    """(k, level, coef) as a table of at most d * d rows."""
    return spark.createDataFrame(inversion_matrix(d, s), "k int, level int, coef long")


def solve(levels: DataFrame, d: int, s: int) -> DataFrame:
    """(level, x) from (level, z), where z is a level's moment less its self-pairs on the population's scale; stays lazy."""
    coef = F.broadcast(coefficients(levels.sparkSession, d, s))
    return levels.join(coef, "level").groupBy("k").agg(F.sum(F.col("coef") * F.col("z")).alias("x")).withColumnRenamed("k", "level")
