"""Competing estimators: all pairs, record-pair sampling, signature patterns, LSH strata, half-sum bound."""

from __future__ import annotations

import math
import random
from collections.abc import Callable, Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pairlattice.functions.hashing import md5_60
from pairlattice.operators import moments, strata, subvalues
from pairlattice.operators.records import agreement, attributes, canonicalized, numbered
from pairlattice.plans import estimate
from pairlattice.spec import EstimatorSpec


def _agreeing(d: int, null_policy: str = "equal") -> Column:
    return agreement([F.col(f"l.a{i}") for i in range(1, d + 1)], [F.col(f"r.a{i}") for i in range(1, d + 1)], null_policy)


def all_pairs(df: DataFrame, attrs: Sequence[str], record_id: str, most_rows: int = 20_000, null_policy: str = "equal") -> DataFrame:
    """(level, x): ordered pairs by agreement, exact at every size.

    Equal records are one vector with a number, and the vectors are compared one by one.  Where more than
    ``most_rows`` of them are different, the pairs are counted by subsets of attributes instead, without
    hashes: the same numbers, and no step that grows with the square of the rows.
    """
    d, cols = len(attrs), [f"a{i + 1}" for i in range(len(attrs))]
    base = canonicalized(df, attrs, record_id, null_policy)
    vectors = base.groupBy(*cols).agg(F.count(F.lit(1)).alias("c"))
    if vectors.limit(most_rows + 1).count() > most_rows:
        return counted_pairs(base, cols, null_policy)
    vectors = vectors.withColumn("v", F.xxhash64(*[F.isnull(c) for c in cols], *cols)).repartition(df.sparkSession.sparkContext.defaultParallelism)
    l, r = vectors.alias("l"), F.broadcast(vectors.alias("r"))
    before = (F.col("l.v") < F.col("r.v")) | ((F.col("l.v") == F.col("r.v")) & (F.struct(*[F.col(f"l.{c}") for c in cols]) < F.struct(*[F.col(f"r.{c}") for c in cols])))
    product = lambda a, b: F.col(a).cast("decimal(19,0)") * b.cast("decimal(19,0)")
    unlike = l.join(r, before).groupBy(_agreeing(d, null_policy).alias("level")).agg(F.sum(F.lit(2) * product("l.c", F.col("r.c"))).alias("x"))
    itself = agreement([F.col(c) for c in cols], [F.col(c) for c in cols], null_policy).alias("level")
    alike = vectors.where("c > 1").groupBy(itself).agg(F.sum(product("c", F.col("c") - 1)).alias("x"))
    return unlike.unionByName(alike).groupBy("level").agg(F.sum("x").cast("long").alias("x"))


def counted_pairs(base: DataFrame, cols: Sequence[str], null_policy: str) -> DataFrame:
    """The same from the moments of all subsets; pairs that agree on nothing are the rest of n (n - 1)."""
    spec = EstimatorSpec(s=1, null_policy=null_policy, fingerprint="raw")
    got = estimate.self_join_size(base, cols, spec, "exact", "rid").select("level", F.col("x").cast("decimal(38,0)").alias("x"), "n")
    n = F.max(F.col("n").cast("decimal(19,0)"))
    none = got.agg((n * (n - 1)).cast("decimal(38,0)").alias("every"), F.sum("x").alias("some")).select(F.lit(0).alias("level"), (F.col("every") - F.col("some")).alias("x"))
    return got.select("level", "x").unionByName(none).where("x > 0").select("level", F.col("x").cast("long").alias("x"))


# ---- record sampling ------------------------------------------------------------------------


def draw_order(rid: Column, seed: Column, oracle: bool) -> Column:
    return md5_60(F.concat_ws("|", F.concat(F.lit("p"), seed.cast("string")), rid.cast("string"))) if oracle else F.xxhash64(seed, rid)


def seeded(df: DataFrame, seeds: Sequence[int]) -> DataFrame:
    """``df`` once for each seed, in a column."""
    return df.withColumn("seed", F.explode(F.array(*[F.lit(int(k)) for k in seeds])))


def least(base: DataFrame, want: int, seeds: Sequence[int], oracle: bool) -> DataFrame:
    """The ``want`` records of least hash for each seed.

    Cells of hashes are counted first; records below the cell in which the sample ends are taken as
    they are, only those of that cell are ranked.
    """
    bits = 16 if len(seeds) == 1 else 10
    h = seeded(base, seeds).withColumn("_h", draw_order(F.col("rid"), F.col("seed"), oracle))
    h = h.withColumn("_cell", F.shiftright("_h", (60 if oracle else 64) - bits))
    ends, left = {}, dict.fromkeys(map(int, seeds), want)
    for r in h.groupBy("seed", "_cell").agg(F.count(F.lit(1)).alias("c")).orderBy("seed", "_cell").collect():  # cells x seeds rows
        if left[r["seed"]] > 0:
            ends[r["seed"]] = r["_cell"], left[r["seed"]]
            left[r["seed"]] -= r["c"]
    if not ends:
        return h.drop("_h", "_cell").limit(0)
    last = base.sparkSession.createDataFrame([(k, c, x) for k, (c, x) in ends.items()], "seed int, _end long, _rest long")
    near = h.join(F.broadcast(last), "seed").where("_cell <= _end")
    rank = F.row_number().over(Window.partitionBy("seed").orderBy("_h", "rid"))
    edge = near.where("_cell = _end").withColumn("_rank", rank).where("_rank <= _rest").drop("_rank")
    return near.where("_cell < _end").unionByName(edge).drop("_h", "_cell", "_end", "_rest")


def pair_sampling(df: DataFrame, attrs: Sequence[str], spec: EstimatorSpec, record_id: str, size: int | Callable[[int], int] | None = None, fraction: float | None = None, bytes: float | None = None, engine: str = "pairs", oracle: bool = False, most: int = 20_000, seeds: Sequence[int] | None = None) -> DataFrame:
    """Profile from records drawn without replacement: the pairs of the sample scaled by n(n-1) / (R(R-1)).

    R is ``size``, a function of n, a ``fraction`` of n, or as many records as fit in ``bytes``.  The
    records with the least hashes are the sample, so partial samples merge.  ``engine='lattice'``
    counts the sample's pairs by the lattice, with the same numbers and no quadratic step.  ``seeds``
    makes a sample for each of them, told by a column ``seed``.
    """
    attrs = attributes(df, attrs)
    d, many = len(attrs), [spec.seed] if seeds is None else list(seeds)
    base = canonicalized(df, attrs, record_id, spec.null_policy)
    n = base.count()
    if bytes is not None:
        from pairlattice.measures import record_bytes
        from pairlattice.plans.bounds import sample_size_for_bytes

        want = sample_size_for_bytes(bytes, max(1.0, record_bytes(df, attrs)))
    else:
        want = round(fraction * n) if fraction is not None else size(n) if callable(size) else int(size)
    want = min(want, n)
    if engine == "pairs" and want > most:
        raise ValueError(f"a sample of {want} has too many pairs; use engine='lattice'")
    sample = least(base, want, many, oracle)
    if engine == "lattice":
        cols = [f"a{i}" for i in range(1, d + 1)]
        x = estimate.repeated(sample, cols, EstimatorSpec(s=spec.s, null_policy=spec.null_policy), "rid", None, "exact").select("seed", "level", "x")
    else:
        spread = sample.repartition(df.sparkSession.sparkContext.defaultParallelism)  # few rows, many pairs
        pairs = spread.alias("l").join(F.broadcast(sample.alias("r")), (F.col("l.seed") == F.col("r.seed")) & (F.col("l.rid") < F.col("r.rid")))
        x = pairs.groupBy(F.col("l.seed").alias("seed"), _agreeing(d, spec.null_policy).alias("level")).agg((F.lit(2.0) * F.count(F.lit(1))).alias("x"))
    scale = F.lit(n * (n - 1) / (want * (want - 1)) if want > 1 else None).cast("double")
    out = completed(x, many, spec.s, d).select("seed", "level", (F.col("x") * scale).alias("x"))
    out = cumulated(out, F.lit(n)).select("seed", "level", "x", "g", F.lit(n).cast("long").alias("n"), F.lit(want).cast("long").alias("sample"))
    return out if seeds is not None else out.drop("seed")


def completed(x: DataFrame, seeds: Sequence[int], s: int, d: int) -> DataFrame:
    """(seed, level, x) with a row for every seed and level."""
    every = x.sparkSession.createDataFrame([(int(q), k) for q in seeds for k in range(s, d + 1)], "seed int, level int")
    return F.broadcast(every).join(x, ["seed", "level"], "left").select("seed", "level", F.coalesce("x", F.lit(0.0)).alias("x"))


def cumulated(x: DataFrame, n: Column) -> DataFrame:
    """``x`` with ``g``: pairs of this level and above, and self-pairs."""
    down = Window.partitionBy("seed").orderBy(F.desc("level")).rowsBetween(Window.unboundedPreceding, 0)  # d rows at most
    return x.withColumn("g", F.sum("x").over(down) + n)


# ---- signature patterns ---------------------------------------------------------------------


def signature_patterns(df: DataFrame, attrs: Sequence[str], s: int, min_support: int = 2, miner: str = "partition", overlap: str = "lattice", tail: str = "none", record_id: str | None = None, sample: float = 0.1, oracle: bool = False) -> DataFrame:
    """(level, patterns, pair_sum, x): pairs that match frequent patterns with at least ``s`` constants.

    ``overlap='none'`` adds up f(f-1) and counts pairs several times; ``lattice`` takes the overlap of
    levels out exactly for the patterns kept.  ``tail='powerlaw'`` adds low supports by a line through
    log counts.  ``miner``: see :func:`patterns`.
    """
    attrs = attributes(df, attrs)
    d = len(attrs)
    found = patterns(df, attrs, s, min_support, miner, sample, record_id, oracle)
    per = found.groupBy("level").agg(F.count(F.lit(1)).alias("patterns"), F.sum(F.col("c") * (F.col("c") - 1)).cast("double").alias("pair_sum"))
    if tail == "powerlaw":
        per = per.join(power_tail(found, min_support), "level", "left").withColumn("pair_sum", F.col("pair_sum") + F.coalesce("tail", F.lit(0.0))).drop("tail")
    every = df.sparkSession.createDataFrame([(k,) for k in range(s, d + 1)], "level int")
    per = F.broadcast(every).join(per, "level", "left").fillna(0, ["patterns"]).fillna(0.0, ["pair_sum"])
    if overlap == "none":
        return per.withColumn("x", F.col("pair_sum"))
    from pairlattice.lattice import solve

    return per.join(F.broadcast(solve(per.select("level", F.col("pair_sum").alias("z")), d, s)), "level")


def patterns(df: DataFrame, attrs: Sequence[str], s: int, min_support: int, miner: str = "partition", sample: float = 0.1, record_id: str | None = None, oracle: bool = False, parts: int = 8, slack: float = 0.5) -> DataFrame:
    """(level, mask, fp, c): frequent patterns; ``fp`` stands for the constants.

    ``levelwise``: a count for each level, of candidates whose parts are all frequent.
    ``partition``: a pattern that is frequent is frequent, in proportion, in one of ``parts`` parts of
    the records at least; such candidates are found first and counted in full after.
    ``sample``: candidates from a share of the records, at half the support in proportion, counted in full.
    ``lossy``: one pass; each part forgets patterns it holds no more often than its share of ``slack`` x
    the support, so counts fall short by at most ``slack`` x support in all; patterns that may reach the
    support are given, with their short counts.
    Without a key, equal rows are told apart by their occurrence number.
    """
    d = len(attrs)
    if record_id is None:
        df, record_id = numbered(df.select(*attrs), "_rid"), "_rid"
    stream = subvalues.level_stream(df, attrs, EstimatorSpec(s=1 if miner == "levelwise" else s, fingerprint="md5_60" if oracle else "xx64"), record_id)
    draw = (lambda what: md5_60(F.concat(F.lit(f"{what}|"), F.col("rid").cast("string")))) if oracle else (lambda what: F.xxhash64(F.lit(what), "rid"))
    if miner in ("partition", "lossy"):
        part = F.pmod(draw("part"), F.lit(parts)).alias("part")
        local = stream.groupBy("level", "mask", "fp", part).agg(F.count(F.lit(1)).alias("c"))
        size = local.groupBy("mask", "part").agg(F.sum("c").alias("held"))  # every record has each mask once
        total = size.groupBy("mask").agg(F.sum("held").alias("n"))
        local = local.join(F.broadcast(size.join(total, "mask")), ["mask", "part"])
        if miner == "partition":
            near = local.where(F.col("c") * F.col("n") >= F.lit(min_support) * F.col("held")).select("mask", "fp").distinct()
            return moments.counts(stream.join(near, ["mask", "fp"], "left_semi")).where(F.col("c") >= min_support)
        held = local.where(F.col("c") * F.col("n") > F.lit(slack * min_support) * F.col("held"))
        return held.groupBy("level", "mask", "fp").agg(F.sum("c").alias("c")).where(F.col("c") >= (1 - slack) * min_support)
    if miner == "sample":
        part = stream.where(F.pmod(draw("sample"), F.lit(1000)) < int(1000 * sample))
        near = moments.counts(part).where(F.col("c") >= max(1, math.floor(min_support * sample * 0.5))).select("mask", "fp")
        return moments.counts(stream.join(near, ["mask", "fp"], "left_semi")).where(F.col("c") >= min_support)
    if miner != "levelwise":
        raise ValueError("miner is levelwise, partition, sample or lossy")
    out, frequent = None, None
    for k in range(1, d + 1):
        at = stream.where(F.col("level") == k)
        if frequent is not None:  # the frequent parts of a record meet as one array; no table is broadcast, as the size of a stream is not told by its file's
            below = stream.where(F.col("level") == k - 1).join(frequent.hint("merge"), ["mask", "fp"], "left_semi").groupBy("rid").agg(F.collect_list("mask").alias("parts"))
            within = F.filter("parts", lambda m: m.bitwiseAND(F.col("mask")) == m)
            at = at.join(below.hint("merge"), "rid").where(F.size(within) == k)
        got = moments.counts(at).where(F.col("c") >= min_support)
        frequent = got.select("mask", "fp")
        if k >= s:
            out = got if out is None else out.unionByName(got)
    return out


def power_tail(found: DataFrame, min_support: int) -> DataFrame:
    """(level, tail): sum of f(f-1) over supports 2 .. min_support - 1 by a power law fitted to the frequent ones."""
    freq = found.groupBy("level", "c").agg(F.count(F.lit(1)).alias("m"))
    x, y = F.log(F.col("c").cast("double")), F.log(F.col("m").cast("double"))
    line = freq.groupBy("level").agg(F.regr_slope(y, x).alias("b"), F.regr_intercept(y, x).alias("a"))
    if min_support <= 2:
        return line.select("level", F.lit(0.0).alias("tail"))
    low = F.explode(F.sequence(F.lit(2), F.lit(min_support - 1)))
    return line.select("level", "a", "b", low.alias("f")).groupBy("level").agg(F.sum(F.exp(F.col("a") + F.col("b") * F.log("f")) * F.col("f") * (F.col("f") - 1)).alias("tail"))


# ---- LSH strata -----------------------------------------------------------------------------


def chosen_columns(d: int, n_hash_cols: int | None, seed: int) -> list[int]:
    return sorted(random.Random(seed).sample(range(1, d + 1), n_hash_cols or max(1, (d + 1) // 2)))


def bucketed(base: DataFrame, d: int, seeds: Sequence[int], n_hash_cols: int | None, oracle: bool) -> DataFrame:
    """``base`` for each seed with ``bucket``, the hash of the seed's columns: column sampling is the hash family of Hamming distance."""
    mask = F.create_map(*[F.lit(x) for k in seeds for x in (int(k), sum(1 << i for i in chosen_columns(d, n_hash_cols, k)))])
    out = seeded(base, seeds).withColumn("_m", mask[F.col("seed")])
    if oracle:
        value = lambda i: F.coalesce(F.col(f"a{i}").cast("string"), F.lit("~"))
    else:
        value = lambda i: F.xxhash64(F.isnull(f"a{i}"), F.col(f"a{i}"))
    cols = [F.when(F.col("_m").bitwiseAND(F.lit(1 << i)) != 0, value(i)) for i in range(1, d + 1)]
    return out.withColumn("bucket", md5_60(F.concat_ws("|", *cols)) if oracle else F.xxhash64("_m", *cols)).drop("_m")


def lsh_buckets(df: DataFrame, attrs: Sequence[str], record_id: str, n_hash_cols: int | None = None, seed: int = 7, oracle: bool = False, null_policy: str = "equal") -> DataFrame:
    """(rid, a1..ad, bucket): records by the values of some attributes."""
    return bucketed(canonicalized(df, attrs, record_id, null_policy), len(attrs), [seed], n_hash_cols, oracle).drop("seed")


def lsh_strata(df: DataFrame, attrs: Sequence[str], spec: EstimatorSpec, record_id: str, n_hash_cols: int | None = None, policy: str = "linear", fraction: float = 0.005, sizes: tuple[int, int] | None = None, adaptive: bool = False, min_hits: int | None = None, seeds: Sequence[int] | None = None, oracle: bool = False) -> DataFrame:
    """Profile from pairs drawn within buckets and across them, each stratum scaled to its number of pairs.

    Records that fit every task as packed words are broadcast, and pairs are drawn and compared there
    (:mod:`pairlattice.operators.strata`); more records are joined, with the same draws and results.

    Two passes: one to count buckets, one to look up the drawn records.  Where they are joined, a record is found by its
    place in the order of buckets (tables of records are never broadcast: each seed has all of them, and
    Spark would take them for as small as the file); within a bucket records are numbered by cells of their hash, so a
    bucket of any size is dealt to many tasks.  ``policy='linear'`` draws n pairs of each stratum,
    ``fraction`` a share of all pairs.  Across buckets two records are drawn each; pairs that share a
    bucket are left out and the others scaled by their number.  ``adaptive`` scales the low stratum
    only if ``min_hits`` (log2 n) of its pairs reach the threshold; with fewer the pairs seen are
    all that is counted, a lower bound.  ``seeds``: an estimate for each, told by a column ``seed``.
    """
    attrs = attributes(df, attrs)
    d, many, spark = len(attrs), [spec.seed] if seeds is None else list(seeds), df.sparkSession
    base = canonicalized(df, attrs, record_id, spec.null_policy)
    hashed = md5_60(F.concat_ws("|", F.lit("o"), F.col("rid").cast("string"))) if oracle else F.xxhash64(F.lit("o"), "rid")
    masks = {int(k): sum(1 << i for i in chosen_columns(d, n_hash_cols, k)) for k in many}

    def planned(n: int, high: int) -> tuple[int, int, int]:
        """Pairs across buckets, and the draws of both strata."""
        low = n * (n - 1) // 2 - high
        m_high, m_low = sizes or ((n, n) if policy == "linear" else (max(1, round(fraction * high)), max(1, round(fraction * low))))
        return low, m_high if high else 0, math.ceil(m_low * n * n / (2 * low)) if low else 0

    def told(plan: list[tuple]) -> DataFrame:
        return F.broadcast(spark.createDataFrame([p[:6] for p in plan], "seed int, n long, high long, low long, m_high long, tries long"))

    records = packed_records(base, d, masks, hashed, oracle, spec)
    if records is not None:
        held = spark.sparkContext.broadcast(records)
        high_of = strata.sizes(spark, held, sorted(set(masks.values())))
        plan = [(k, records.n, high_of[m][0], *planned(records.n, high_of[m][0])) for k, m in masks.items()]
        sizes_of = told(plan)
        found = spark.createDataFrame(strata.hits(spark, held, [(p[0], masks[p[0]], p[4], p[5]) for p in plan], oracle), "seed int, level int, hits long, stratum string")
        held.destroy()
    else:
        found, sizes_of = joined_pairs(base, d, spec, many, n_hash_cols, hashed, oracle, planned, told)
    every = Window.partitionBy("seed", "stratum")
    found = found.withColumn("drawn", F.sum("hits").over(every)).withColumn("reach", F.sum(F.when(F.col("level") >= spec.s, F.col("hits")).otherwise(0)).over(every)).join(sizes_of, "seed")
    scale = F.when(F.col("stratum") == "high", F.col("high")).otherwise(F.col("low")) / F.col("drawn")
    if adaptive:
        enough = F.lit(min_hits) if min_hits else F.greatest(F.lit(1), F.ceil(F.log2(F.greatest(F.col("n"), F.lit(2)).cast("double"))))
        scale = F.when((F.col("stratum") == "low") & (F.col("reach") < enough), F.lit(1.0)).otherwise(scale)
    x = found.groupBy("seed", "level").agg(F.sum(F.col("hits") * 2.0 * scale).alias("x"))
    out = cumulated(completed(x, many, spec.s, d).join(sizes_of, "seed"), F.col("n"))
    out = out.select("seed", "level", "x", "g", "n", F.col("high").alias("pairs_high"), F.col("low").alias("pairs_low"))
    return out if seeds is not None else out.drop("seed")


def packed_records(base: DataFrame, d: int, masks: dict[int, int], hashed: Column, oracle: bool, spec: EstimatorSpec) -> strata.Packed | None:
    """The records for :mod:`strata`, where they fit and nulls agree."""
    if spec.null_policy == "never" or oracle and len(set(masks.values())) > 4:
        return None
    value = lambda i: F.coalesce(F.col(f"a{i}").cast("string"), F.lit("~"))
    buckets = {m: md5_60(F.concat_ws("|", *[value(i) for i in range(1, d + 1) if m >> i & 1])) for m in set(masks.values())} if oracle else {}
    return strata.packed(base, d, hashed, buckets)


def joined_pairs(base: DataFrame, d: int, spec: EstimatorSpec, many: list[int], n_hash_cols: int | None, hashed: Column, oracle: bool, planned: Callable, told: Callable) -> tuple[DataFrame, DataFrame]:
    """(seed, level, hits, stratum) of the drawn pairs by joins, and the sizes of each seed."""
    spark = base.sparkSession
    placed = bucketed(base, d, many, n_hash_cols, oracle)
    placed = placed.withColumn("_h", hashed).withColumn("_cell", F.shiftright("_h", 54 if oracle else 58))
    cells = placed.groupBy("seed", "bucket", "_cell").agg(F.count(F.lit(1)).alias("c"))
    two = (F.col("b") * (F.col("b") - 1) / 2).cast("long")
    size = cells.groupBy("seed", "bucket").agg(F.sum("c").alias("b")).withColumn("pairs", two)
    plan = []
    for r in size.groupBy("seed").agg(F.sum("b").alias("n"), F.sum("pairs").alias("high"), F.count(F.lit(1)).alias("buckets")).collect():  # a row for each seed
        plan.append((r["seed"], r["n"], r["high"], *planned(r["n"], r["high"]), r["buckets"]))
    plan = plan or [(int(k), 0, 0, 0, 0, 0, 0) for k in many]
    sizes_of = told(plan)
    # within a bucket: records before a cell of hashes, then the rank within
    before = Window.partitionBy("seed", "bucket").orderBy("_cell").rowsBetween(Window.unboundedPreceding, -1)
    first = cells.select("seed", "bucket", "_cell", F.coalesce(F.sum("c").over(before), F.lit(0)).alias("_first"))
    inside = placed.withColumn("_rank", F.row_number().over(Window.partitionBy("seed", "bucket", "_cell").orderBy("_h", "rid")) - 1)
    inside = inside.join(first.hint("merge"), ["seed", "bucket", "_cell"]).withColumn("k", F.col("_first") + F.col("_rank"))
    starts = running(size, max(p[6] for p in plan), 60 if oracle else 64)

    def drawn(m: str, total: str, what: str) -> DataFrame:
        draw = md5_60(F.concat_ws("|", F.concat(F.lit(what), F.col("seed").cast("string")), F.col("id").cast("string"))) if oracle else F.xxhash64("seed", F.lit(what), "id")
        most = max(p[4] if m == "m_high" else p[5] for p in plan)
        return spark.range(most).crossJoin(sizes_of).where(F.col("id") < F.col(m)).select("seed", "id", F.pmod(draw, F.col(total)).alias("at"))

    def looked_up(ends: DataFrame, side: str) -> DataFrame:
        cols = [F.col(f"a{i}").alias(f"{side}{i}") for i in range(1, d + 1)]
        held = inside.select("seed", F.col("bucket").alias(f"{side}_bucket"), F.col("k").alias(f"{side}_k"), *cols)
        return ends.join(held.hint("merge"), ["seed", f"{side}_bucket", f"{side}_k"])

    def hits(ends: DataFrame, stratum: str) -> DataFrame:
        same = agreement([F.col(f"l{i}") for i in range(1, d + 1)], [F.col(f"r{i}") for i in range(1, d + 1)], spec.null_policy)
        return looked_up(looked_up(ends, "l"), "r").groupBy("seed", same.alias("level")).agg(F.count(F.lit(1)).alias("hits")).withColumn("stratum", F.lit(stratum))

    pick = located(drawn("m_high", "high", "h"), starts, "pair_start", "pairs")
    # ordinal within the bucket to a pair: row a has the pairs a(a-1)/2 .. a(a+1)/2 - 1
    o, a = F.col("at") - F.col("pair_start"), F.col("a")
    pick = pick.withColumn("o", o).withColumn("a", F.floor((F.sqrt(8.0 * o + 1) + 1) / 2).cast("long"))
    pick = pick.withColumn("a", F.when(a * (a - 1) / 2 > F.col("o"), a - 1).when(a * (a + 1) / 2 <= F.col("o"), a + 1).otherwise(a))
    within = pick.select("seed", "id", F.col("bucket").alias("l_bucket"), F.col("a").alias("l_k"), F.col("bucket").alias("r_bucket"), (F.col("o") - (a * (a - 1) / 2).cast("long")).alias("r_k"))
    one = lambda what, side: located(drawn("tries", "n", what), starts, "start", "b").select("seed", "id", F.col("bucket").alias(f"{side}_bucket"), (F.col("at") - F.col("start")).alias(f"{side}_k"))
    across = one("l", "l").join(one("r", "r").hint("merge"), ["seed", "id"]).where("l_bucket <> r_bucket")
    return hits(within, "high").unionByName(hits(across, "low")), sizes_of


def running(size: DataFrame, buckets: int, hash_bits: int, per_group: int = 50_000) -> DataFrame:
    """Buckets of each seed with the records (``start``) and pairs (``pair_start``) before them, in the order of their hashes.

    Two steps: sums of groups of neighbouring hashes, then within a group; the number of groups follows that of buckets.
    """
    bits = max(0, math.ceil(math.log2(max(1, buckets / per_group))))
    g = size.withColumn("grp", F.shiftright("bucket", hash_bits - bits) if bits else F.lit(0).cast("long"))
    per = g.groupBy("seed", "grp").agg(F.sum("b").alias("gb"), F.sum("pairs").alias("gp"))
    w = Window.partitionBy("seed").orderBy("grp").rowsBetween(Window.unboundedPreceding, -1)  # as many rows as groups
    per = per.select("seed", "grp", F.coalesce(F.sum("gb").over(w), F.lit(0)).alias("gb"), F.coalesce(F.sum("gp").over(w), F.lit(0)).alias("gp"))
    inner = Window.partitionBy("seed", "grp").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    return g.join(per.hint("merge"), ["seed", "grp"]).select("seed", "bucket", "b", "pairs", (F.col("gb") + F.coalesce(F.sum("b").over(inner), F.lit(0))).alias("start"), (F.col("gp") + F.coalesce(F.sum("pairs").over(inner), F.lit(0))).alias("pair_start"))


def located(drawn: DataFrame, starts: DataFrame, start: str, width: str, cells: int = 4096, keys: Sequence[str] = ("seed",)) -> DataFrame:
    """Each drawn ordinal ``at`` with the bucket that holds it: a range join on the cells of a grid.

    A bucket is listed in every cell that its range [start, start + width) touches, an ordinal stands in one cell.
    """
    held = starts.where(F.col(width) > 0).select(*keys, "bucket", F.col(start).alias("start_"), (F.col(start) + F.col(width)).alias("end_"), start)
    step = held.agg(F.greatest(F.lit(1), F.ceil(F.max("end_") / cells))).first()[0] or 1
    cell = F.floor(F.col("start_") / step)
    held = held.withColumn("cell", F.explode(F.sequence(cell, F.floor((F.col("end_") - 1) / step))))
    return drawn.withColumn("cell", F.floor(F.col("at") / step)).join(held.hint("merge"), [*keys, "cell"]).where((F.col("at") >= F.col("start_")) & (F.col("at") < F.col("end_"))).drop("cell", "start_", "end_")


def half_sum_bound(a: DataFrame, b: DataFrame, attrs: Sequence[str], s: int) -> DataFrame:
    """(bound, join): half the sum of the self-join sizes, which bounds an equi-join but not a similarity join, beside the true size."""
    spec = EstimatorSpec(s=s)
    g = lambda df: estimate.self_join_size(df, attrs, spec, "exact").where(F.col("level") == s).select(F.col("g").cast("double").alias("g"))
    true = estimate.join_size(a, b, attrs, attrs, spec, "exact").where(F.col("level") == s).select(F.col("pairs_at_least").cast("double").alias("j"))
    return g(a).withColumnRenamed("g", "ga").crossJoin(g(b).withColumnRenamed("g", "gb")).crossJoin(true).select(((F.col("ga") + F.col("gb")) / 2).alias("bound"), F.col("j").alias("join_size"))
