"""Variance bounds, sizes of sketches and samples, and analytical costs."""

from __future__ import annotations

import math
from math import comb

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pairlattice.spec import sub_values


def spread(d: int, s: int) -> float:
    return comb(d, s) ** 2 * comb(2 * (d - s), d - s)


def variance_exact(d: int, s: int, r: float, g: float) -> float:
    """Bound of var(G / g) with exact moments of samples."""
    return spread(d, s) / r / g


def variance_sketch(d: int, s: int, r: float, w: int, g: float, n: float | None = None, n_over_g: float | None = None) -> float:
    """Bound of var(G / g) with one row of ``w`` counters; n / g may be given itself (0 drops it)."""
    share = n_over_g if n_over_g is not None else n / g
    return spread(d, s) / r * ((1 + 2 / w) / g + 2 / w * (1 + share / r) ** 2)


def variance_join(var_y: dict[int, float], d: int, s: int, r: float = 1.0) -> dict[int, float]:
    """Bound of each level of a join by the recursion over higher levels, covariances left out."""
    out: dict[int, float] = {}
    for k in range(d, s - 1, -1):
        out[k] = var_y[k] / r**4 + sum(comb(j, k) ** 2 * out[j] for j in range(k + 1, d + 1))
    return out


def variance_inner_product(sj_a: float, sj_b: float, width: int = 1) -> float:
    return 2 * sj_a * sj_b / width


def min_sample_size(n: int) -> int:
    """Records a sample needs at least for errors under 100 %."""
    return math.isqrt(n) + (math.isqrt(n) ** 2 < n)


def grid(sizes: DataFrame) -> DataFrame:
    """Bound curves over d and s: exact, sketch at r = 1, sketch at r = 0.1, both with w = 1000 and n / g dropped.

    ``sizes`` has (d, g): for each number of attributes a size that no level falls below, such as that of the pairs that agree on all.
    """

    def curves(d: int, g: int) -> list[tuple[int, float, float, float]]:
        return [(s, variance_exact(d, s, 1, g), variance_sketch(d, s, 1, 1000, g, n_over_g=0), variance_sketch(d, s, 0.1, 1000, g, n_over_g=0)) for s in range(1, d + 1)]

    of = F.udf(curves, "array<struct<s: int, exact: double, sketch: double, sketch_tenth: double>>")
    return sizes.select("d", F.col("g").cast("long").alias("g")).select("d", "g", F.explode(of("d", "g")).alias("c")).select("d", "g", "c.*")


def size_sketch(eps: float, fail_prob: float, d: int, s: int, ratio: float = 1.0) -> tuple[int, int]:
    """(width, depth) for a relative error ``eps`` but with probability ``fail_prob``."""
    width = math.ceil(8 * spread(d, s) / (ratio * eps * eps))
    depth = math.ceil(8 * math.log(1 / fail_prob))
    return width, depth + 1 - depth % 2


def ratio_for_budget(d: int, s: int, budget: int) -> dict[int, float]:
    """Ratio of each level at which a record emits at most ``budget`` sub-values of it: constant work per record."""
    return {k: min(1.0, budget / comb(d, k)) for k in range(s, d + 1)}


def sketch_bytes(d: int, s: int, width: int, depth: int, counter_bytes: int = 4) -> int:
    return (d - s + 1) * width * depth * counter_bytes


def sample_size_for_bytes(total: float, record_bytes: float) -> int:
    return int(total // record_bytes)


def sample_exponent(n: int, p: float) -> int:
    """Records of a sample of n^(p / (p + 1))."""
    return round(n ** (p / (p + 1)))


def matching_exponent(n: int, size: int) -> float:
    """The e with n^e = size."""
    return math.log(size) / math.log(n)


def per_record(d: int, s: int, ratio: float = 1.0, depth: int = 3) -> tuple[float, float]:
    """(sub-values, counter updates) of a record."""
    return ratio * sub_values(d, s), ratio * depth * sub_values(d, s)


def asymptotic_grid(sizes: DataFrame, d: int = 5) -> DataFrame:
    """Operations of the lattice estimator and of pair sampling as n grows: p = 2 with s = d - 1, p = 3 with s = d - 2; ``sizes`` has n."""
    plans = sizes.sparkSession.createDataFrame([(p, d - p + 1, sub_values(d, d - p + 1), 2 * p / (p + 1)) for p in (2, 3)], "p int, s int, each long, power double")
    return sizes.select("n").crossJoin(plans).select("n", "p", "s", (F.col("n") * F.col("each")).cast("double").alias("lattice"), F.pow(F.col("n").cast("double"), "power").alias("sampling"))


#: Passes over the data.
PASSES = {"lattice": 1, "join": 1, "pair_sampling": 1, "lsh_strata": 2, "signature_partition": 2, "signature_sample": 2, "signature_lossy": 2, "all_pairs": 1}


def advise(profile_rows: list[dict], n: int, pair_limit: float = 1e8) -> str:
    """A hint for a similarity join from its estimated size: compare all pairs, block by attributes, or do not run."""
    g = max(r["g"] for r in profile_rows)
    if float(n) * n <= pair_limit:
        return "nested loop"
    return "block by attribute subsets" if g <= 50.0 * n else "too many pairs: raise the threshold"
