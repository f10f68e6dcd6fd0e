"""Texts as vectors of super-shingles: min-hashes of token shingles, several joined into a feature."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def tokens(text: Column) -> Column:
    return F.split(F.trim(F.lower(F.coalesce(text, F.lit("")))), r"\s+")


def shingle_set(text: Column, q: int = 1) -> Column:
    """Distinct shingles of ``q`` tokens; a shorter text is one shingle."""
    t = tokens(text)
    if q == 1:
        return F.array_distinct(t)
    one = lambda w: F.transform(F.sequence(F.lit(1), F.greatest(F.lit(1), F.size(w) - (q - 1))), lambda i: F.array_join(F.slice(w, i, q), " "))
    return F.array_distinct(F.element_at(F.transform(F.array(t), one), 1))


def super_shingles(shingles: Column, features: int = 6, m: int = 1, oracle: bool = False) -> list[Column]:
    """``features`` columns, each of ``m`` min-hashes of the set; ``oracle`` uses hex digests that every engine computes."""
    out = []
    for f in range(features):
        parts = []
        for j in range(m):
            if oracle:
                parts.append(F.array_min(F.transform(shingles, lambda x: F.md5(F.concat(F.lit(f"{f}|{j}|"), x)))))  # noqa: B023
            else:
                parts.append(F.array_min(F.transform(shingles, lambda x: F.xxhash64(F.lit(f * 64 + j), x))))  # noqa: B023
        out.append(F.concat(*parts) if oracle else parts[0] if m == 1 else F.xxhash64(*parts))
    return out


def super_shingles_sql(text: str, features: int = 6) -> str:
    """The (1, 1) features in SQL."""
    s = f"list_distinct(string_split_regex(trim(lower({text})), '\\s+'))"
    return ", ".join(f"list_min(list_transform({s}, lambda z: md5('{f}|0|' || z))) AS a{f + 1}" for f in range(features))
