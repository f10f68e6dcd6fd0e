"""Choice of attributes when there are too many for the lattice."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairlattice.operators.records import attributes


def choose_attributes(df: DataFrame, attrs, m: int, rule: str = "max_distinct", seed: int = 7) -> list[str]:
    """``m`` of the attributes: the first, random ones, or those with the most distinct values (one approximate pass)."""
    attrs = attributes(df, attrs)
    if rule == "first":
        return attrs[:m]
    if rule == "random":
        import random

        return sorted(random.Random(seed).sample(attrs, m), key=attrs.index)
    got = df.agg(*[F.approx_count_distinct(a).alias(a) for a in attrs]).first()
    return sorted(sorted(attrs, key=lambda a: (-got[a], attrs.index(a)))[:m], key=attrs.index)
