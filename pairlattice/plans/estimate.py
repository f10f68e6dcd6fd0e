"""Similarity profiles: pair counts per level and sizes per threshold, exact or by sketches."""

from __future__ import annotations

from collections.abc import Sequence
from math import comb

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pairlattice import lattice
from pairlattice.operators import moments, repeats, sketch, subvalues
from pairlattice.operators.records import attributes
from pairlattice.spec import EstimatorSpec


def per_level(d: int, spec: EstimatorSpec, value) -> Column:
    out = F.lit(None).cast("double")
    for k in range(spec.s, d + 1):
        out = F.when(F.col("level") == k, F.lit(float(value(k)))).otherwise(out)
    return out


def profile(levels: DataFrame, d: int, spec: EstimatorSpec) -> DataFrame:
    """One row per level s..d from (level, y, emitted, n): all thresholds from one run.

    ``x``: pairs that agree on exactly ``level`` attributes; ``pairs_at_least``: on at least that
    many, without self-pairs; ``g`` with them; ``selectivity``: g of all n * n pairs.
    """
    exact = all(spec.ratio_of(k) == 1 for k in range(spec.s, d + 1)) and spec.self_pairs == "emitted"
    number = "decimal(38,0)" if exact and dict(levels.dtypes)["y"].startswith("decimal") else "double"
    known = F.col("emitted").cast(number) if spec.self_pairs == "emitted" else (per_level(d, spec, lambda k: spec.ratio_of(k) * comb(d, k)) * F.col("n")).cast(number)
    z = F.col("y").cast(number) - known
    if number == "double":
        z = z / per_level(d, spec, lambda k: spec.ratio_of(k) ** 2)
    if spec.clamp == "cascade":
        solved = cascade(levels, d, spec)
    else:
        solved = lattice.solve(levels.select("level", z.alias("z")), d, spec.s)
        if spec.clamp == "final":
            solved = solved.withColumn("x", F.greatest(F.lit(0).cast(dict(solved.dtypes)["x"]), "x"))
    out = levels.join(F.broadcast(solved), "level")
    down = Window.orderBy(F.desc("level")).rowsBetween(Window.unboundedPreceding, 0)  # d rows at most
    half = F.lit(2) if spec.pair_counting == "unordered" else F.lit(1)
    out = out.withColumn("pairs_at_least", F.sum("x").over(down))
    return out.select(
        "level", "y", "emitted", "n", (F.col("x") / half if spec.pair_counting == "unordered" else F.col("x")).alias("x"),
        (F.col("pairs_at_least") / half if spec.pair_counting == "unordered" else F.col("pairs_at_least")).alias("pairs_at_least"),
        (F.col("pairs_at_least") + F.col("n")).alias("g"),
        ((F.col("pairs_at_least") + F.col("n")).cast("double") / F.nullif(F.col("n").cast("double") * F.col("n").cast("double"), F.lit(0.0))).alias("selectivity"),
    )


def cascade(levels: DataFrame, d: int, spec: EstimatorSpec) -> DataFrame:
    """Levels solved on the driver from d rows, each made non-negative before the next."""
    got = {r["level"]: r for r in levels.select("level", F.col("y").cast("double").alias("y"), "emitted", "n").collect()}
    known = {k: float(r["emitted"]) if spec.self_pairs == "emitted" else spec.ratio_of(k) * comb(d, k) * r["n"] for k, r in got.items()}
    x = lattice.invert_sampled({k: r["y"] for k, r in got.items()}, known, d, spec.s, {k: spec.ratio_of(k) for k in got}, "cascade") if got else {}
    return levels.sparkSession.createDataFrame(list(x.items()), "level int, x double")


def with_n(levels: DataFrame, n: DataFrame) -> DataFrame:
    return levels.crossJoin(F.broadcast(n))  # one row


def all_levels(levels: DataFrame, d: int, s: int) -> DataFrame:
    """Levels without a sub-value count nothing."""
    every = levels.sparkSession.createDataFrame([(k,) for k in range(s, d + 1)], "level int")
    return F.broadcast(every).join(levels, "level", "left").fillna(0, ["emitted"]).withColumn("y", F.coalesce("y", F.lit(0).cast(dict(levels.dtypes)["y"])))


def self_join_size(df: DataFrame, attrs: Sequence[str] | str, spec: EstimatorSpec, mode: str = "sketch", record_id: str | None = None, engine: str = "sql") -> DataFrame:
    """Profile of one relation in one scan.

    ``exact`` counts sub-values (shuffles their distinct values, right for samples and windows);
    ``sketch`` keeps counters only (the shuffle does not grow with n).
    """
    attrs = attributes(df, attrs)
    d = len(attrs)
    spec.check(d)
    stream = subvalues.level_stream(df, attrs, spec, record_id, count_level=True)
    if mode == "exact":
        all_ = moments.level_moments(stream)
        zero, levels = all_.where("level = 0").select(F.col("emitted").alias("n")), all_.where("level > 0")
    elif mode == "sketch":
        built = sketch.build_arrow(stream, spec) if engine == "arrow" else sketch.build(stream, spec)
        levels, zero = sketch.second_moment(built, spec), sketch.level_sizes(built).where("level = 0").select(F.col("emitted").alias("n"))
    else:
        raise ValueError("mode is exact or sketch")
    return profile(all_levels(with_n(levels, zero.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"))), d, spec.s).fillna(0, ["n"]), d, spec)


def from_sketch(built: DataFrame, d: int, spec: EstimatorSpec) -> DataFrame:
    """Profile of a stored, merged or streamed sketch."""
    levels, zero = sketch.second_moment(built, spec), sketch.level_sizes(built).where("level = 0").agg(F.coalesce(F.sum("emitted"), F.lit(0)).alias("n"))
    return profile(all_levels(with_n(levels, zero), d, spec.s).fillna(0, ["n"]), d, spec)


def profiles_by(levels: DataFrame, keys: Sequence[str], d: int, spec: EstimatorSpec) -> DataFrame:
    """(keys.., level, y, emitted, n, x, pairs_at_least, g): a profile for each value of ``keys`` (windows, seeds) from (keys.., level, y, emitted, n)."""
    every = levels.sparkSession.createDataFrame([(k,) for k in range(spec.s, d + 1)], "level int")
    full = levels.select(*keys, "n").distinct().crossJoin(F.broadcast(every)).join(levels.drop("n"), [*keys, "level"], "left")
    full = full.select(*keys, "level", F.coalesce(F.col("y").cast("double"), F.lit(0.0)).alias("y"), F.coalesce("emitted", F.lit(0).cast("long")).alias("emitted"), "n")
    known = F.col("emitted").cast("double") if spec.self_pairs == "emitted" else per_level(d, spec, lambda k: spec.ratio_of(k) * comb(d, k)) * F.col("n")
    z = full.select(*keys, "level", ((F.col("y") - known) / per_level(d, spec, lambda k: spec.ratio_of(k) ** 2)).alias("z"))
    coef = F.broadcast(lattice.coefficients(levels.sparkSession, d, spec.s))
    solved = z.join(coef, "level").groupBy(*keys, "k").agg(F.sum(F.col("coef") * F.col("z")).alias("x")).withColumnRenamed("k", "level")
    down = Window.partitionBy(*keys).orderBy(F.desc("level")).rowsBetween(Window.unboundedPreceding, 0)  # d rows at most
    out = full.join(solved, [*keys, "level"]).withColumn("pairs_at_least", F.sum("x").over(down))
    return out.withColumn("g", F.col("pairs_at_least") + F.col("n"))


def from_sketches(built: DataFrame, keys: Sequence[str], d: int, spec: EstimatorSpec) -> DataFrame:
    """A profile for each value of ``keys`` from sketches that carry these columns."""
    n = sketch.level_sizes(built, keys).where("level = 0").select(*keys, F.col("emitted").alias("n"))
    return profiles_by(sketch.second_moment(built, spec, keys).join(n, list(keys)), keys, d, spec)


def repeated(df: DataFrame, attrs: Sequence[str] | str, spec: EstimatorSpec, record_id: str, seeds: Sequence[int] | None, mode: str = "sketch") -> DataFrame:
    """Profiles of repeated estimates, one for each seed, in one plan with ``seed`` as a group key.

    ``seeds=None``: ``df`` has a column ``seed`` already, which groups its records.
    """
    attrs = attributes(df, attrs)
    d = len(attrs)
    spec.check(d)
    fast = seeds is not None and repeats.fits(df, spec, record_id)
    if fast and mode == "sketch":
        return from_sketches(repeats.counters(df, attrs, spec, record_id, seeds), ["seed"], d, spec)
    if fast and mode == "exact":
        all_ = repeats.moments(df, attrs, spec, record_id, seeds)
    else:
        base = df if seeds is None else df.select(record_id, *attrs).withColumn("seed", F.explode(subvalues.int_array(seeds)))
        stream = subvalues.level_stream(base, attrs, spec, record_id, True, ["seed"], F.col("seed"))
        if mode == "sketch":
            up = sketch.updates(stream, spec, ["seed"], seeds)
            return from_sketches(up.groupBy("seed", "level", "row", "bucket").agg(F.sum("sign").alias("counter")), ["seed"], d, spec)
        all_ = moments.level_moments(stream, ["seed"])
    n = all_.where("level = 0").select("seed", F.col("emitted").alias("n"))
    return profiles_by(all_.where("level > 0").join(n, "seed"), ["seed"], d, spec)


def join_profile(levels: DataFrame, d: int, spec: EstimatorSpec, na: DataFrame, nb: DataFrame, spec_b: EstimatorSpec | None = None) -> DataFrame:
    """Profile of a join from (level, y): no self-pairs, each pair once; both sides must be drawn, so their ratios multiply."""
    other = spec_b or spec
    exact = dict(levels.dtypes)["y"].startswith("decimal") and all(spec.ratio_of(k) == other.ratio_of(k) == 1 for k in range(spec.s, d + 1))
    z = F.col("y") if exact else F.col("y").cast("double") / per_level(d, spec, lambda k: spec.ratio_of(k) * other.ratio_of(k))
    every = all_levels(levels.withColumn("emitted", F.lit(0)), d, spec.s).drop("emitted")
    out = every.join(F.broadcast(lattice.solve(every.select("level", z.alias("z")), d, spec.s)), "level").crossJoin(F.broadcast(na.select(F.col("n").alias("na")))).crossJoin(F.broadcast(nb.select(F.col("n").alias("nb"))))
    down = Window.orderBy(F.desc("level")).rowsBetween(Window.unboundedPreceding, 0)
    out = out.withColumn("pairs_at_least", F.sum("x").over(down))
    return out.select("level", "y", "x", "pairs_at_least", (F.col("pairs_at_least").cast("double") / F.nullif(F.col("na").cast("double") * F.col("nb").cast("double"), F.lit(0.0))).alias("selectivity"))


def join_size(a: DataFrame, b: DataFrame, attrs_a: Sequence[str], attrs_b: Sequence[str], spec: EstimatorSpec, mode: str = "sketch", id_a: str | None = None, id_b: str | None = None, engine: str = "group", ratio_b: float | dict | None = None) -> DataFrame:
    """Profile of the similarity join of two relations whose attributes correspond by position.

    ``exact`` with ``engine='group'`` counts both sides in one aggregation, with ``join`` it joins two
    count tables.  ``ratio_b`` draws the second relation at another ratio; its draws have a seed of
    their own, so that records with equal ids draw alike only by chance.
    """
    attrs_a, attrs_b = attributes(a, attrs_a), attributes(b, attrs_b)
    kinds = [[dict(x.dtypes)[c] for c in cols] for x, cols in ((a, attrs_a), (b, attrs_b))]
    if kinds[0] != kinds[1]:
        raise ValueError(f"attributes of both sides need equal types: {kinds[0]} and {kinds[1]}")
    d = len(attrs_a)
    sa = subvalues.level_stream(a, attrs_a, spec, id_a, count_level=True)
    spec_b = spec.with_(seed=spec.seed + 1, ratio=spec.ratio if ratio_b is None else ratio_b)
    sb = subvalues.level_stream(b, attrs_b, spec_b.check(d), id_b, count_level=True)
    if mode == "sketch":
        ka, kb = sketch.build(sa, spec), sketch.build(sb, spec)
        size = lambda k: sketch.level_sizes(k).where("level = 0").agg(F.coalesce(F.sum("emitted"), F.lit(0)).alias("n"))
        return join_profile(sketch.inner_product(ka, kb, spec), d, spec, size(ka), size(kb), spec_b)
    if engine == "join":
        ca, cb = moments.counts(sa), moments.counts(sb)
        both = ca.withColumnRenamed("c", "ca").join(cb.withColumnRenamed("c", "cb"), ["level", "mask", "fp"])
        size = lambda c: c.where("level = 0").agg(F.coalesce(F.sum("c"), F.lit(0)).alias("n"))
        na, nb = size(ca), size(cb)
    else:
        both = sa.withColumn("side", F.lit(0)).unionByName(sb.withColumn("side", F.lit(1))).groupBy("level", "mask", "fp").agg(F.sum(F.when(F.col("side") == 0, 1).otherwise(0)).alias("ca"), F.sum("side").cast("long").alias("cb"))
        size = lambda c: both.where("level = 0").agg(F.coalesce(F.sum(c), F.lit(0)).alias("n"))
        na, nb = size("ca"), size("cb")
    product = F.sum(F.col("ca").cast("decimal(19,0)") * F.col("cb").cast("decimal(19,0)")).cast("decimal(38,0)")
    return join_profile(both.where("level > 0").groupBy("level").agg(product.alias("y")), d, spec, na, nb, spec_b)


def profile_gaps(prof: DataFrame) -> DataFrame:
    """(level, g, gap, growth): what each lower threshold adds."""
    w = Window.orderBy(F.desc("level"))
    before = F.lag("g").over(w)
    return prof.select("level", "g", (F.col("g") - before).alias("gap"), (F.col("g").cast("double") / F.nullif(before.cast("double"), F.lit(0.0))).alias("growth"))


def sanity(prof: DataFrame, d: int, spec: EstimatorSpec, floor: float = 2.0) -> DataFrame:
    """``prof`` with ``noise``, the sketch's standard deviation of a level, and whether ``x`` stands above ``floor`` of it."""
    noise = F.col("y").cast("double") * F.lit((2.0 / spec.width) ** 0.5) / per_level(d, spec, lambda k: spec.ratio_of(k) ** 2)
    return prof.withColumn("noise", noise).withColumn("reliable", F.col("x").cast("double") >= floor * F.col("noise"))


def materialize_levels(df: DataFrame, attrs: Sequence[str], spec: EstimatorSpec, path: str, record_id: str | None = None) -> None:
    """Write the level streams, partitioned by level, for several passes over one sample."""
    subvalues.level_stream(df, attrs, spec, record_id).write.mode("overwrite").partitionBy("level").parquet(path)
