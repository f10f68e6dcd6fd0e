"""Records: canonical attribute values, nulls, identity, agreement and Hamming distance."""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


def attributes(df: DataFrame, attrs: Sequence[str] | str) -> list[str]:
    """Attribute columns; ``*`` takes all of atomic type."""
    if attrs == "*":
        return [f.name for f in df.schema.fields if not isinstance(f.dataType, (T.ArrayType, T.MapType, T.StructType))]
    return list(attrs)


def canonical(column: Column, kind: T.DataType) -> Column:
    """Equal values get equal forms: -0.0 is 0.0, all NaN are one, maps are sorted entries."""
    if isinstance(kind, (T.FloatType, T.DoubleType)):
        return F.when(F.isnan(column), F.lit(float("nan"))).otherwise(column + F.lit(0.0))
    if isinstance(kind, T.MapType):
        return F.array_sort(F.map_entries(column))
    return column


def canonicalized(df: DataFrame, attrs: Sequence[str], record_id: str | None = None, null_policy: str = "equal", keep: Sequence[str] = ()) -> DataFrame:
    """(rid, a1..ad, keep..): the attributes in order; ``rid`` is a hash of the key where one is named, else of the whole row.

    Without a key equal rows would draw alike; :func:`numbered` tells them apart.
    """
    kinds = {f.name: f.dataType for f in df.schema.fields}
    rid = F.col(record_id) if record_id else F.xxhash64(*[F.isnull(c) for c in df.columns], *[canonical(F.col(c), kinds[c]) for c in df.columns])
    out = df.select(rid.alias("rid"), *[canonical(F.col(a), kinds[a]).alias(f"a{i + 1}") for i, a in enumerate(attrs)], *keep)
    if null_policy == "drop":
        out = out.dropna(subset=[f"a{i + 1}" for i in range(len(attrs))])
    return out


def numbered(df: DataFrame, name: str = "rid") -> DataFrame:
    """``df`` with an identity for tables without a key: hash of the whole row and the occurrence number among equal rows.

    Costs a shuffle by row hash; equal rows meet, so a value repeated without bound needs a key instead.
    """
    from pyspark.sql import Window

    h = F.xxhash64(*[F.isnull(c) for c in df.columns], *df.columns)
    return df.withColumn("_h", h).withColumn("_k", F.row_number().over(Window.partitionBy("_h").orderBy(*df.columns))).withColumn(name, F.xxhash64("_h", "_k")).drop("_h", "_k")


def agreement(a: Sequence[Column], b: Sequence[Column], null_policy: str = "equal") -> Column:
    """Number of attributes on which two records agree."""
    same = (lambda x, y: x.eqNullSafe(y)) if null_policy == "equal" else (lambda x, y: F.coalesce(x == y, F.lit(False)))
    out = F.lit(0)
    for x, y in zip(a, b, strict=True):
        out = out + same(x, y).cast("int")
    return out


def hamming_distance(a: Sequence[Column], b: Sequence[Column]) -> Column:
    return F.lit(len(a)) - agreement(a, b)


def hamming_similarity(a: Sequence[Column], b: Sequence[Column]) -> Column:
    """Share of attributes on which two records agree."""
    return agreement(a, b) / F.lit(len(a))


def hamming_bits(a: Column, b: Column) -> Column:
    """Hamming distance of two integers as bit strings."""
    return F.bit_count(a.bitwiseXOR(b))


def threshold_from_similarity(d: int, share: float) -> int:
    """Least number of common attributes for a similarity of at least ``share``."""
    return max(0, math.ceil(share * d - 1e-9))


def encoded(column: Column) -> Column:
    """Unambiguous text of a value: its length, a colon, the value; ``n`` for null."""
    text = column.cast("string")
    return F.coalesce(F.concat(F.length(text).cast("string"), F.lit(":"), text), F.lit("n"))


def encoded_sql(column: str) -> str:
    return f"coalesce(length(CAST({column} AS VARCHAR)) || ':' || CAST({column} AS VARCHAR), 'n')"
