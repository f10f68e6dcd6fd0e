"""Functions for SQL sessions."""

from __future__ import annotations

from math import comb

from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def register(spark: SparkSession) -> None:
    """``binomial(n, k)`` and the table function ``similarity_profile_of(y, n, d, s)`` that inverts an array of level moments s..d."""
    from pyspark.sql.functions import udtf

    @F.pandas_udf(T.LongType())
    def binomial(n, k):
        return n.combine(k, lambda a, b: comb(int(a), int(b)))

    @udtf(returnType="level int, x double")
    class SimilarityProfileOf:
        def eval(self, y: list, n: int, d: int, s: int):
            from pairlattice.lattice import invert_moments

            for level, x in invert_moments({s + i: v for i, v in enumerate(y)}, n, d, s).items():
                yield level, float(x)

    spark.udf.register("binomial", binomial)
    spark.udtf.register("similarity_profile_of", SimilarityProfileOf)
