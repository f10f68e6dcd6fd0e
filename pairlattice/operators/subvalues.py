"""Sub-values: projections of records on attribute subsets, tagged, drawn and fingerprinted in one narrow pass."""

from __future__ import annotations

import math
from collections.abc import Sequence
from math import comb

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pairlattice.functions.hashing import md5_60, uniform
from pairlattice.lattice import masks, subsets
from pairlattice.operators.records import attributes, canonicalized, encoded
from pairlattice.spec import EstimatorSpec

TOP = 1 << 60


def draw_hash(spec: EstimatorSpec, rid: Column, key: Column, what: str, seed: Column | None = None) -> Column:
    """A number in [0, 2^60) fixed by the record's identity, so that retries draw alike and equal records do not."""
    seed = F.lit(spec.seed) if seed is None else seed
    if spec.fingerprint == "md5_60":
        return md5_60(F.concat_ws("|", F.concat(F.lit(what), seed.cast("string")), rid.cast("string"), key.cast("string")))
    return uniform(seed, F.lit(what), rid, key) % F.lit(TOP)


def int_array(values: Sequence[int]) -> Column:
    return F.array(*[F.lit(v) for v in values]) if values else F.array().cast("array<int>")


def drawn_masks(d: int, spec: EstimatorSpec, rid: Column, seed: Column | None = None) -> Column:
    """Array of the subset masks that a record emits, before the independent draws; ``seed`` replaces that of ``spec``."""
    if spec.sampler == "bernoulli" or all(spec.ratio_of(k) == 1 for k in range(spec.s, d + 1)) and spec.sampler == "fixed":
        return int_array(masks(d, spec.s))
    parts = []
    for k in range(spec.s, d + 1):
        want = spec.ratio_of(k) * comb(d, k)
        low, extra = math.floor(want + 1e-12), want - math.floor(want + 1e-12)
        more = (draw_hash(spec, rid, F.lit(k), "n", seed) < F.lit(int(extra * TOP))).cast("int") if extra > 1e-12 else F.lit(0)
        if spec.sampler == "replacement":
            parts.append(replacement(spec, rid, int_array(subsets(d, k)), comb(d, k), k, F.lit(low) + more, seed))
        else:  # one struct for each subset, sorted by its draw; no lambda, so it stays in generated code
            ranked = F.sort_array(F.array(*[F.struct(draw_hash(spec, rid, F.lit(m), "m", seed).alias("h"), F.lit(m).alias("m")) for m in subsets(d, k)]))
            parts.append(F.slice(ranked, F.lit(1), F.lit(low) + more).getField("m"))
    return F.concat(*parts)


def replacement(spec: EstimatorSpec, rid: Column, all_of: Column, size: int, level: int, count: Column, seed: Column | None = None) -> Column:
    picks = F.when(count > 0, F.sequence(F.lit(1), count)).otherwise(F.array().cast("array<int>"))
    return F.transform(picks, lambda i: F.get(all_of, (draw_hash(spec, rid, i + F.lit(1000 * level), "r", seed) % F.lit(size)).cast("int")))


def cells(df: DataFrame, d: int, spec: EstimatorSpec) -> list[Column]:
    """One value per attribute that stands for it in every subset."""
    if spec.fingerprint == "xx64":
        return [F.xxhash64(F.isnull(f"a{i}"), F.col(f"a{i}")) for i in range(1, d + 1)]
    return [encoded(F.col(f"a{i}")) for i in range(1, d + 1)]


def fingerprint(mask: Column, d: int, spec: EstimatorSpec) -> Column:
    """The sub-value of a subset: cells outside it are null and skipped, the mask tags it."""
    chosen = [F.when(mask.bitwiseAND(F.lit(1 << i)) != 0, F.col(f"c{i + 1}")) for i in range(d)]
    if spec.fingerprint == "xx64":
        return F.xxhash64(mask, *chosen)
    text = F.concat(mask.cast("string"), F.lit("|"), F.concat_ws("", *chosen))
    return md5_60(text) if spec.fingerprint == "md5_60" else text


def level_stream(df: DataFrame, attrs: Sequence[str] | str, spec: EstimatorSpec, record_id: str | None = None, count_level: bool = False, keep: Sequence[str] = (), seed: Column | None = None) -> DataFrame:
    """(rid, keep.., level, mask, fp): every sub-value of every record at levels s..d, as drawn; one scan, no shuffle.

    With ``count_level`` each record also emits level 0 once, whose count is n.  ``keep`` names columns
    that go along; ``seed`` is a column of seeds that replaces that of ``spec``.
    """
    attrs = attributes(df, attrs)
    d = len(attrs)
    spec.check(d)
    base = canonicalized(df, attrs, record_id, spec.null_policy, keep)
    all_masks = drawn_masks(d, spec, F.col("rid"), seed)
    base = base.withColumn("_masks", F.concat(F.array(F.lit(0)), all_masks) if count_level else all_masks)
    if spec.null_policy == "never":
        missing = sum((F.when(F.isnull(f"a{i + 1}"), F.lit(1 << i)).otherwise(F.lit(0)) for i in range(d)), F.lit(0))
        base = base.withColumn("_missing", missing)
    more = ["_missing"] if spec.null_policy == "never" else []
    out = base.select("rid", *keep, *[c.alias(f"c{i + 1}") for i, c in enumerate(cells(base, d, spec))], *more, F.explode("_masks").alias("mask"))
    if spec.null_policy == "never":
        out = out.where(F.col("mask").bitwiseAND(F.col("_missing")) == 0)
    out = out.withColumn("level", F.bit_count("mask").cast("int"))
    if spec.sampler == "bernoulli" and any(spec.ratio_of(k) < 1 for k in range(spec.s, d + 1)):
        limit = F.lit(TOP)
        for k in range(spec.s, d + 1):
            limit = F.when(F.col("level") == k, F.lit(int(spec.ratio_of(k) * TOP))).otherwise(limit)
        # records themselves, at level 0, are not drawn
        out = out.where((F.col("level") == 0) | (draw_hash(spec, F.col("rid"), F.col("mask"), "m", seed) < limit))
    return out.select("rid", *keep, "level", "mask", fingerprint(F.col("mask"), d, spec).alias("fp"))
