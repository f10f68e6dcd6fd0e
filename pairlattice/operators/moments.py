"""Exact second moments: of a bag, of each attribute subset, of each level."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pairlattice.lattice import subsets
from pairlattice.operators.records import attributes
from pairlattice.operators.subvalues import level_stream
from pairlattice.spec import EstimatorSpec

BIG = "decimal(38,0)"


def square_sum(c: str) -> Column:
    """Sum of squares without overflow."""
    return F.sum(F.col(c).cast("decimal(19,0)") * F.col(c).cast("decimal(19,0)")).cast(BIG)


def second_moment(df: DataFrame, cols: Sequence[str]) -> DataFrame:
    """(n, distinct, f2) of the bag of value tuples."""
    return df.groupBy(*cols).agg(F.count(F.lit(1)).alias("c")).agg(F.sum("c").alias("n"), F.count("c").alias("distinct"), square_sum("c").alias("f2"))


def counts(stream: DataFrame, keys: Sequence[str] = ()) -> DataFrame:
    """(keys.., level, mask, fp, c): multiplicities of sub-values, combined before the shuffle."""
    return stream.groupBy(*keys, "level", "mask", "fp").agg(F.count(F.lit(1)).alias("c"))


def level_moments(stream: DataFrame, keys: Sequence[str] = ()) -> DataFrame:
    """(keys.., level, y, emitted) of a level stream, or of one for each value of ``keys``."""
    return counts(stream, keys).groupBy(*keys, "level").agg(square_sum("c").alias("y"), F.sum("c").alias("emitted"))


def projection_moments(df: DataFrame, attrs: Sequence[str] | str, k: int, null_policy: str = "equal") -> DataFrame:
    """(mask, n, distinct, f2, matching): each subset of ``k`` attributes; matching pairs are f2 - n."""
    attrs = attributes(df, attrs)
    spec = EstimatorSpec(s=k, null_policy=null_policy)
    stream = level_stream(df, attrs, spec).where(F.col("level") == k)
    out = counts(stream).groupBy("mask").agg(F.sum("c").alias("n"), F.count("c").alias("distinct"), square_sum("c").alias("f2"))
    return out.withColumn("matching", F.col("f2") - F.col("n"))


def projection_moments_sql(df: DataFrame, attrs: Sequence[str], k: int) -> DataFrame:
    """The same by grouping sets; Catalyst copies each row once per subset with all its columns."""
    d = len(attrs)
    sets = ", ".join("(" + ", ".join(f"`{attrs[i]}`" for i in range(d) if m >> i & 1) + ")" for m in subsets(d, k))
    gid = " + ".join(f"(CASE WHEN grouping(`{a}`) = 0 THEN {1 << i} ELSE 0 END)" for i, a in enumerate(attrs))
    cols = ", ".join(f"`{a}`" for a in attrs)
    got = df.sparkSession.sql(f"SELECT {gid} AS mask, count(*) AS c FROM {{t}} GROUP BY {cols} GROUPING SETS ({sets})", t=df.select(*attrs))
    out = got.groupBy("mask").agg(F.sum("c").alias("n"), F.count("c").alias("distinct"), square_sum("c").alias("f2"))
    return out.withColumn("matching", F.col("f2") - F.col("n"))


def cube_moments(df: DataFrame, attrs: Sequence[str], rollup: bool = False) -> DataFrame:
    """(mask, n, f2) of every subset (the cube) or every prefix (the rollup)."""
    grouped = df.rollup(*attrs) if rollup else df.cube(*attrs)
    bits = sum((F.when(F.grouping(a) == 0, F.lit(1 << i)).otherwise(F.lit(0)) for i, a in enumerate(attrs)), F.lit(0))
    return grouped.agg(bits.alias("mask"), F.count(F.lit(1)).alias("c")).groupBy("mask").agg(F.sum("c").alias("n"), square_sum("c").alias("f2"))


def projection_skew(df: DataFrame, attrs: Sequence[str] | str, k: int) -> DataFrame:
    """Subsets of ``k`` attributes by skew: share of pairs that match, effective number of values, rank."""
    out = projection_moments(df, attrs, k)
    share = F.col("f2").cast("double") / (F.col("n").cast("double") * F.col("n").cast("double"))
    return out.select("mask", "n", "distinct", "f2", share.alias("match_share"), (F.lit(1.0) / share).alias("effective_values"), F.rank().over(Window.orderBy(F.desc("f2"), "mask")).alias("rank"))


def soft_dependencies(df: DataFrame, attrs: Sequence[str] | str, k: int) -> DataFrame:
    """(mask, added, kept): of the pairs that match on ``mask``, the share that also match on one more attribute; near 1 means it follows."""
    attrs = attributes(df, attrs)
    below, above = projection_moments(df, attrs, k).select("mask", "f2"), projection_moments(df, attrs, k + 1).select(F.col("mask").alias("up"), F.col("f2").alias("g2"))
    pairs = below.join(above, (F.col("mask").bitwiseAND(F.col("up")) == F.col("mask")))
    added = F.log2(F.col("up").bitwiseXOR(F.col("mask"))).cast("int")
    return pairs.select("mask", added.alias("added"), (F.col("g2").cast("double") / F.col("f2").cast("double")).alias("kept"))


def column_cardinalities(df: DataFrame, attrs: Sequence[str] | str, exact: bool = True) -> DataFrame:
    """(attribute, n_distinct) of each attribute."""
    attrs = attributes(df, attrs)
    f = F.count_distinct if exact else F.approx_count_distinct
    one = df.agg(*[f(F.col(a)).alias(a) for a in attrs])
    return one.select(F.explode(F.array(*[F.struct(F.lit(a).alias("attribute"), F.col(a).alias("n_distinct")) for a in attrs])).alias("x")).select("x.*")
