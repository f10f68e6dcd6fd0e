"""Registered queries of the estimators, baselines, measures and streams, and their SQL."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable
from dataclasses import dataclass
from functools import partial, reduce
from itertools import combinations
from math import comb

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pairlattice import lattice, measures
from pairlattice.functions import hashing
from pairlattice.functions.shingles import shingle_set
from pairlattice.operators import baselines, moments, records, sketch, subvalues
from pairlattice.operators.records import encoded_sql
from pairlattice.plans import bounds, estimate
from pairlattice.plans.attributes import choose_attributes
from pairlattice.sources import workloads as W
from pairlattice.spec import EstimatorSpec, sub_values
from pairlattice.streaming import profile as stream_profile

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
ORDERS5 = W.TABLES["orders5"]
MD5 = EstimatorSpec(s=3, fingerprint="md5_60")


def add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def longs(df: DataFrame, *names: str) -> DataFrame:
    return df.withColumns({n: F.round(F.col(n).cast("decimal(38,4)")).cast("long") for n in names})


def shaped(prof: DataFrame) -> DataFrame:
    """Profile columns that every engine prints alike."""
    return longs(prof, "y", "emitted", "n", "x", "pairs_at_least", "g").select(F.col("level").cast("long").alias("level"), "y", "emitted", "n", "x", "pairs_at_least", "g", F.round("selectivity", 9).alias("selectivity"))


# ---- SQL of profiles ------------------------------------------------------------------------


def cols_of(d: int, mask: int) -> list[str]:
    return [f"a{i + 1}" for i in range(d) if mask >> i & 1]


def level_sql(d: int, s: int, source: str = "t") -> str:
    """(level, y, emitted) by one GROUP BY per subset."""
    parts = []
    for m in lattice.masks(d, s):
        cols = ", ".join(cols_of(d, m))
        parts.append(f"SELECT {m.bit_count()} AS level, sum(c * c) AS y, sum(c) AS emitted FROM (SELECT count(*) AS c FROM {source} GROUP BY {cols})")
    return f"SELECT level, CAST(coalesce(sum(y), 0) AS BIGINT) AS y, CAST(coalesce(sum(emitted), 0) AS BIGINT) AS emitted FROM ({' UNION ALL '.join(parts)}) GROUP BY level"


def solved_sql(d: int, s: int, levels: str, n: str = "(SELECT count(*) FROM t)", factor: str = "1", known: str = "emitted") -> str:
    coef = ", ".join(f"({k}, {j}, {c})" for k, j, c in lattice.inversion_matrix(d, s))
    return f"""
, lv AS ({levels}), nn AS (SELECT CAST({n} AS BIGINT) AS n),
cf(k, level, coef) AS (VALUES {coef}),
xs AS (SELECT k AS level, sum(coef * (y - {known}) * {factor}) AS x FROM cf JOIN lv USING (level) GROUP BY k),
pr AS (SELECT lv.level, y, emitted, n, x, sum(x) OVER (ORDER BY lv.level DESC) AS p FROM lv JOIN xs USING (level), nn)
SELECT CAST(level AS BIGINT) AS level, CAST(round(y) AS BIGINT) AS y, CAST(emitted AS BIGINT) AS emitted, n, CAST(round(x) AS BIGINT) AS x, CAST(round(p) AS BIGINT) AS pairs_at_least,
  CAST(round(p + n) AS BIGINT) AS g, round(CAST(p + n AS DOUBLE) / (CAST(n AS DOUBLE) * n), 9) AS selectivity FROM pr"""


def profile_sql(source: str, d: int, s: int = 1) -> str:
    return f"WITH t AS ({source})" + solved_sql(d, s, level_sql(d, s))


def exact(frame: Callable[[SparkSession, str], DataFrame], d: int, s: int = 1, **kw) -> Query:
    cols = [f"a{i + 1}" for i in range(d)]
    return lambda spark, sf: shaped(estimate.self_join_size(frame(spark, sf), cols, EstimatorSpec(s=s, **kw), "exact", "rid"))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The lattice estimator in sketch mode over orders: all thresholds from three attributes up, one scan."""
    return estimate.self_join_size(ORDERS5.frame(spark, sf_dir), ORDERS5.cols, EstimatorSpec(s=3), "sketch", "rid")


# ---- moments --------------------------------------------------------------------------------

add("f2_orders_custkey", lambda sp, sf: longs(moments.second_moment(table(sp, sf, "orders"), ["o_custkey"]), "f2"),
    "SELECT CAST(sum(c) AS BIGINT) AS n, count(*) AS \"distinct\", CAST(sum(c * c) AS BIGINT) AS f2 FROM (SELECT count(*) AS c FROM orders GROUP BY o_custkey)")
add("f2_events_pair", lambda sp, sf: longs(moments.second_moment(table(sp, sf, "events"), ["user_id", "event_type"]), "f2"),
    "SELECT CAST(sum(c) AS BIGINT) AS n, count(*) AS \"distinct\", CAST(sum(c * c) AS BIGINT) AS f2 FROM (SELECT count(*) AS c FROM events GROUP BY user_id, event_type)")


def projection_sql(w: W.Workload, k: int) -> str:
    parts = [f"SELECT {m} AS mask, CAST(sum(c) AS BIGINT) AS n, count(*) AS \"distinct\", CAST(sum(c * c) AS BIGINT) AS f2, CAST(sum(c * c) - sum(c) AS BIGINT) AS matching FROM (SELECT count(*) AS c FROM t GROUP BY {', '.join(cols_of(w.d, m))})" for m in lattice.subsets(w.d, k)]
    return f"WITH t AS ({w.sql()}) " + " UNION ALL ".join(parts)


for _k in (3, 4):
    add(f"projection_moments_orders5_k{_k}", lambda sp, sf, k=_k: longs(moments.projection_moments(ORDERS5.frame(sp, sf), ORDERS5.cols, k), "f2", "matching"), projection_sql(ORDERS5, _k))
add("projection_moments_grouping_sets", lambda sp, sf: longs(moments.projection_moments_sql(ORDERS5.frame(sp, sf), ORDERS5.cols, 3), "f2", "matching"), projection_sql(ORDERS5, 3))
add("projection_skew_part5", lambda sp, sf: longs(moments.projection_skew(W.TABLES["part5"].frame(sp, sf), W.TABLES["part5"].cols, 2), "f2").select("mask", "n", "f2", "rank", F.round("match_share", 9).alias("match_share"), F.round("effective_values", 6).alias("effective_values")),
    f"SELECT mask, n, f2, rank() OVER (ORDER BY f2 DESC, mask) AS rank, round(CAST(f2 AS DOUBLE) / (CAST(n AS DOUBLE) * n), 9) AS match_share, round(CAST(n AS DOUBLE) * n / f2, 6) AS effective_values FROM ({projection_sql(W.TABLES['part5'], 2)})")
add("top_skewed_subsets", lambda sp, sf: longs(moments.projection_skew(ORDERS5.frame(sp, sf), ORDERS5.cols, 2), "f2").orderBy("rank").limit(3).select("mask", "n", "f2", "rank"),
    f"SELECT mask, n, f2, rank() OVER (ORDER BY f2 DESC, mask) AS rank FROM ({projection_sql(ORDERS5, 2)}) ORDER BY rank LIMIT 3")
add("soft_dependencies_orders5", lambda sp, sf: moments.soft_dependencies(ORDERS5.frame(sp, sf), ORDERS5.cols, 1).select("mask", "added", F.round("kept", 9).alias("kept")),
    f"SELECT p.mask, CAST(log2(xor(p.mask, q.mask)) AS INT) AS added, round(CAST(q.f2 AS DOUBLE) / p.f2, 9) AS kept FROM ({projection_sql(ORDERS5, 1)}) p JOIN ({projection_sql(ORDERS5, 2)}) q ON p.mask & q.mask = p.mask")
for _n in ("orders5", "events5", "lineitem_mixed6"):
    _w = W.TABLES[_n]
    add(f"column_cardinalities_{_n}", lambda sp, sf, w=_w: moments.column_cardinalities(w.frame(sp, sf), w.cols),
        f"WITH t AS ({_w.sql()}) " + " UNION ALL ".join(f"SELECT 'a{i + 1}' AS attribute, count(DISTINCT a{i + 1}) AS n_distinct FROM t" for i in range(_w.d)))
_c3 = W.TABLES["customer3"]
for _n, _roll in (("cube_customer3", False), ("rollup_customer3", True)):
    _masks = [(1 << i) - 1 for i in range(4)] if _roll else list(range(8))
    add(_n, lambda sp, sf, r=_roll: longs(moments.cube_moments(_c3.frame(sp, sf), _c3.cols, r), "f2"),
        f"WITH t AS ({_c3.sql()}) " + " UNION ALL ".join(f"SELECT {m} AS mask, CAST(sum(c) AS BIGINT) AS n, CAST(sum(c * c) AS BIGINT) AS f2 FROM (SELECT count(*) AS c FROM t{' GROUP BY ' + ', '.join(cols_of(3, m)) if m else ''})" for m in _masks))

# ---- level streams and profiles --------------------------------------------------------------

add("level_stream_counts_orders5", lambda sp, sf: subvalues.level_stream(ORDERS5.frame(sp, sf), ORDERS5.cols, EstimatorSpec(s=3), "rid").groupBy("level", "mask").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("fp").alias("n_distinct")),
    f"WITH t AS ({ORDERS5.sql()}) " + " UNION ALL ".join(f"SELECT {m.bit_count()} AS level, {m} AS mask, CAST(sum(c) AS BIGINT) AS n, count(*) AS n_distinct FROM (SELECT count(*) AS c FROM t GROUP BY {', '.join(cols_of(5, m))})" for m in lattice.masks(5, 3)))
for _n, _w in W.TABLES.items():
    if _n != "nulls3":
        add(f"level_moments_{_n}", lambda sp, sf, w=_w: longs(moments.level_moments(subvalues.level_stream(w.frame(sp, sf), w.cols, EstimatorSpec(s=1), "rid")), "y"), f"WITH t AS ({_w.sql()}) {level_sql(_w.d, 1)}")
        add(f"profile_{_n}", exact(_w.frame, _w.d), profile_sql(_w.sql(), _w.d))
add("profile_doc_shingles6", exact(W.shingle_frame, 6), profile_sql(W.shingle_sql(), 6))
_conv = "conv_id * 10000 + turn"
add("profile_conv_shingles6", exact(partial(W.shingle_frame, table="conversations", rid=_conv), 6), profile_sql(W.shingle_sql("conversations", _conv), 6))
for _n, (_u, _g) in W.GENERATED.items():
    add(f"profile_{_n}", exact(lambda sp, sf, u=_u, g=_g: W.generated_pairs(sp, sf, u, g), 5, 3), profile_sql(W.generated_sql(str(_u), _g), 5, 3))
for _x in (2, 4, 8):
    add(f"profile_dup_x{_x}", exact(lambda sp, sf, x=_x: W.duplicated(ORDERS5.frame(sp, sf), x), 5, 3), profile_sql(f"SELECT t.* FROM ({ORDERS5.sql()}) t, range({_x})", 5, 3))
add("profile_unordered_orders5", lambda sp, sf: longs(estimate.self_join_size(ORDERS5.frame(sp, sf), ORDERS5.cols, EstimatorSpec(s=1, pair_counting="unordered"), "exact", "rid"), "x", "pairs_at_least").select(F.col("level").cast("long").alias("level"), "x", "pairs_at_least"),
    f"SELECT level, CAST(x // 2 AS BIGINT) AS x, CAST(pairs_at_least // 2 AS BIGINT) AS pairs_at_least FROM ({profile_sql(ORDERS5.sql(), 5)})")
add("profile_gaps_orders5", lambda sp, sf: longs(estimate.profile_gaps(estimate.self_join_size(ORDERS5.frame(sp, sf), ORDERS5.cols, EstimatorSpec(s=1), "exact", "rid")), "g", "gap").select(F.col("level").cast("long").alias("level"), "g", "gap", F.round("growth", 6).alias("growth")),
    f"SELECT level, g, g - lag(g) OVER (ORDER BY level DESC) AS gap, round(CAST(g AS DOUBLE) / lag(g) OVER (ORDER BY level DESC), 6) AS growth FROM ({profile_sql(ORDERS5.sql(), 5)})")
_nulls = W.TABLES["nulls3"]
add("profile_nulls_equal", exact(_nulls.frame, 3), profile_sql(_nulls.sql(), 3))
add("profile_nulls_drop", exact(_nulls.frame, 3, null_policy="drop"), profile_sql(f"SELECT * FROM ({_nulls.sql()}) WHERE a1 IS NOT NULL AND a2 IS NOT NULL AND a3 IS NOT NULL", 3))
_never = " UNION ALL ".join(f"SELECT {m.bit_count()} AS level, sum(c * c) AS y, sum(c) AS emitted FROM (SELECT count(*) AS c FROM t WHERE {' AND '.join(c + ' IS NOT NULL' for c in cols_of(3, m))} GROUP BY {', '.join(cols_of(3, m))})" for m in lattice.masks(3, 1))
add("profile_nulls_never", exact(_nulls.frame, 3, null_policy="never"), f"WITH t AS ({_nulls.sql()})" + solved_sql(3, 1, f"SELECT level, CAST(sum(y) AS BIGINT) AS y, CAST(sum(emitted) AS BIGINT) AS emitted FROM ({_never}) GROUP BY level"))

# ---- brute force ----------------------------------------------------------------------------


def pairs_sql(w: W.Workload) -> str:
    same = " + ".join(f"CAST(l.a{i} IS NOT DISTINCT FROM r.a{i} AS INT)" for i in range(1, w.d + 1))
    return f"WITH t AS ({w.sql()}) SELECT {same} AS level, CAST(2 * count(*) AS BIGINT) AS x FROM t l JOIN t r ON l.rid < r.rid GROUP BY 1"


for _n in ("part5", "customer3", "embed8"):
    _w = W.TABLES[_n]
    add(f"all_pairs_{_n}", lambda sp, sf, w=_w: baselines.all_pairs(w.frame(sp, sf), w.cols, "rid"), pairs_sql(_w))


def hamming_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(l, r, distance, similarity): pairs of customers at least 0.6 similar.  Equal records are a class, named by its least id: each other one with its class at distance 0, and the pairs between classes."""
    w = W.TABLES["customer3"]
    t = w.frame(spark, sf_dir)
    reps = t.groupBy(*w.cols).agg(F.min("rid").alias("rid"))
    most, same = 3 - records.threshold_from_similarity(3, 0.6), lambda i: F.col(f"l.a{i}").eqNullSafe(F.col(f"r.a{i}"))
    a, b = [F.col(f"l.a{i}") for i in (1, 2, 3)], [F.col(f"r.a{i}") for i in (1, 2, 3)]
    shown = [F.col("l.rid").alias("l"), F.col("r.rid").alias("r"), records.hamming_distance(a, b).alias("distance"), F.round(records.hamming_similarity(a, b), 3).cast("decimal(4,3)").alias("similarity")]
    inside = reps.alias("l").join(t.alias("r"), reduce(Column.__and__, map(same, (1, 2, 3)))).where("l.rid <> r.rid").select(*shown)
    # classes differ somewhere, so those that agree on all fields but ``most`` = 1 meet on one subset of fields only
    between = [reps.alias("l").join(reps.alias("r"), reduce(Column.__and__, map(same, m))).where("l.rid < r.rid").select(*shown) for m in combinations((1, 2, 3), 3 - most)]
    return reduce(DataFrame.unionByName, between, inside).where(F.col("distance") <= most)


def hamming_sql() -> str:
    w = W.TABLES["customer3"]
    same = " + ".join(f"CAST(l.a{i} IS NOT DISTINCT FROM r.a{i} AS INT)" for i in (1, 2, 3))
    return f"""WITH t AS ({w.sql()}), v AS (SELECT min(rid) AS rid, a1, a2, a3 FROM t GROUP BY a1, a2, a3), p AS (
    SELECT l.rid AS l, r.rid AS r, 3 - ({same}) AS distance FROM v l, v r WHERE l.rid < r.rid AND {same} = 2
    UNION ALL SELECT l.rid, r.rid, 0 FROM v l JOIN t r ON l.a1 IS NOT DISTINCT FROM r.a1 AND l.a2 IS NOT DISTINCT FROM r.a2 AND l.a3 IS NOT DISTINCT FROM r.a3 WHERE l.rid <> r.rid)
SELECT l, r, distance, CAST(CASE distance WHEN 0 THEN 1.0 ELSE 0.667 END AS DECIMAL(4, 3)) AS similarity FROM p"""


add("hamming_pairs_example", hamming_pairs, hamming_sql())

# ---- drawn sub-values -----------------------------------------------------------------------


def draw_sql(seed: int, what: str, key: str) -> str:
    return f"('0x' || substr(md5('{what}{seed}|' || CAST(rid AS VARCHAR) || '|' || CAST({key} AS VARCHAR)), 1, 15))::BIGINT"


@dataclass(frozen=True)
class Source:
    """SQL of (rid, a1..ad, further columns)."""

    text: str
    d: int

    def sql(self) -> str:
        return self.text


def digest_sql(text: str) -> str:
    return f"('0x' || substr(md5({text}), 1, 15))::BIGINT"


def drawn_sql(w: W.Workload | Source, spec: EstimatorSpec, p: str = "", more: str = "") -> str:
    """CTEs ``t`` and ``v`` (rid, level, mask, fp): the sub-values as drawn, fingerprinted by MD5; ``p`` ends their names, ``more`` names columns that go along."""
    d, top, levels = w.d, 1 << 60, range(spec.s, w.d + 1)
    rows, fps = [], []
    for m in lattice.masks(d, spec.s):
        text = " || ".join(encoded_sql(f"a{i + 1}") for i in range(d) if m >> i & 1)
        rows.append(f"({m}, {m.bit_count()})")
        fps.append(f"WHEN {m} THEN {digest_sql(f"'{m}|' || {text}")}")
    pairs = f"SELECT t{p}.*, mask, level FROM t{p}, mk{p}"
    if spec.null_policy == "never":
        pairs += f" WHERE mask & ({' + '.join(f'CASE WHEN a{i + 1} IS NULL THEN {1 << i} ELSE 0 END' for i in range(d))}) = 0"
    low = {k: int(spec.ratio_of(k) * comb(d, k) + 1e-12) for k in levels}
    count = "CASE level " + " ".join(f"WHEN {k} THEN {low[k]} + CASE WHEN {draw_sql(spec.seed, 'n', 'level')} < {int((spec.ratio_of(k) * comb(d, k) - low[k]) * top)} THEN 1 ELSE 0 END" for k in levels) + " END"
    if spec.ratio == 1.0:
        chosen = f"SELECT *, 0 AS pos FROM e{p}"
    elif spec.sampler == "bernoulli":
        limit = " ".join(f"WHEN {k} THEN {int(spec.ratio_of(k) * top)}" for k in levels)
        chosen = f"SELECT *, 0 AS pos FROM e{p} WHERE {draw_sql(spec.seed, 'm', 'mask')} < CASE level {limit} END"
    elif spec.sampler == "replacement":
        all_of = ", ".join(f"({k}, {lattice.subsets(d, k)})" for k in levels)
        pairs = f"SELECT t{p}.*, level, of_ FROM t{p}, (VALUES {all_of}) AS of_(level, of_)"
        chosen = f"SELECT *, of_[1 + {draw_sql(spec.seed, 'r', '(i + 1000 * level)')} % len(of_)] AS mask FROM (SELECT *, unnest(range(1, 1 + {count})) AS i FROM e{p})"
    else:
        chosen = f"SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY rid, level ORDER BY {draw_sql(spec.seed, 'm', 'mask')}, mask) AS pos FROM e{p}) WHERE pos <= {count}"
    return f"""WITH t{p} AS ({w.sql()}), mk{p}(mask, level) AS (VALUES {', '.join(rows)}), e{p} AS ({pairs}), ch{p} AS ({chosen}),
v{p} AS (SELECT rid, {more}level, mask, CASE mask {' '.join(fps)} END AS fp FROM ch{p})"""


COUNTED = "SELECT level, CAST(sum(c * c) AS BIGINT) AS y, CAST(sum(c) AS BIGINT) AS emitted FROM (SELECT level, mask, fp, count(*) AS c FROM v GROUP BY 1, 2, 3) GROUP BY level"


def sampled(name: str, w: W.Workload, spec: EstimatorSpec) -> None:
    factors = " ".join(f"WHEN {k} THEN {1 / spec.ratio_of(k) ** 2!r}" for k in range(spec.s, w.d + 1))
    add(name, lambda sp, sf: shaped(estimate.self_join_size(w.frame(sp, sf), w.cols, spec, "exact", "rid")), drawn_sql(w, spec) + solved_sql(w.d, spec.s, COUNTED, factor=f"CASE level {factors} END"))


sampled("sampled_fixed_orders5_r50", ORDERS5, MD5.with_(ratio=0.5))
sampled("sampled_bernoulli_orders5_r50", ORDERS5, MD5.with_(ratio=0.5, sampler="bernoulli"))
sampled("sampled_perlevel_orders6", W.TABLES["orders6"], MD5.with_(s=4, ratio={4: 0.25, 5: 0.5, 6: 1.0}))
for _r in (25, 75):
    sampled(f"sampled_fixed_orders5_r{_r}", ORDERS5, MD5.with_(ratio=_r / 100))
sampled("sampled_replacement_orders5", ORDERS5, MD5.with_(ratio=0.5, sampler="replacement"))


def expected_vs_emitted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The two self-pair terms of one draw, and the exact profile."""
    f, spec = ORDERS5.frame(spark, sf_dir), MD5.with_(ratio=0.5)
    run = lambda s: shaped(estimate.self_join_size(f, ORDERS5.cols, s, "exact", "rid")).select("level", "g")
    out = run(spec).withColumnRenamed("g", "g_emitted").join(run(spec.with_(self_pairs="expected")).withColumnRenamed("g", "g_expected"), "level")
    return out.join(run(spec.with_(ratio=1.0)).withColumnRenamed("g", "g_true"), "level")


def expected_sql(w: W.Workload, spec: EstimatorSpec) -> str:
    drawn = drawn_sql(w, spec)
    share = "(CASE level " + " ".join(f"WHEN {k} THEN {spec.ratio_of(k) * comb(w.d, k)!r}" for k in range(spec.s, w.d + 1)) + " END * (SELECT n FROM nn))"
    one = lambda known: drawn + solved_sql(w.d, spec.s, COUNTED, factor=repr(1 / spec.ratio**2), known=known)
    return f"SELECT a.level, a.g AS g_emitted, b.g AS g_expected, c.g AS g_true FROM ({one('emitted')}) a JOIN ({one(share)}) b USING (level) JOIN ({profile_sql(w.sql(), w.d, spec.s)}) c USING (level)"


add("sampled_expected_vs_emitted", expected_vs_emitted, expected_sql(ORDERS5, MD5.with_(ratio=0.5)))

# ---- sketches -------------------------------------------------------------------------------


def counter_sql(w: W.Workload | Source, spec: EstimatorSpec, p: str = "", more: str = "") -> str:
    """CTE ``k`` (more.., level, row, bucket, counter) after those of :func:`drawn_sql`."""
    parts = [f"SELECT {more}level, -1 AS row, 0 AS bucket, 1 AS sign FROM v{p}"]
    for r in range(spec.depth):
        b = hashing.tab4_sql(hashing.coefficients(spec.seed, r, "bucket"), "fp")
        s = hashing.tab4_sql(hashing.coefficients(spec.seed, r, "sign"), "fp")
        parts.append(f"SELECT {more}level, {r} AS row, CAST({b} % {spec.width} AS INT) AS bucket, CASE WHEN {s} & 1 = 1 THEN 1 ELSE -1 END AS sign FROM v{p}")
    return f"{drawn_sql(w, spec, p, more)}, k{p} AS (SELECT {more}level, row, bucket, CAST(sum(sign) AS BIGINT) AS counter FROM ({' UNION ALL '.join(parts)}) GROUP BY ALL)"


def built(w: W.Workload, spec: EstimatorSpec, engine: str = "sql") -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        s = subvalues.level_stream(w.frame(spark, sf_dir), w.cols, spec, "rid")
        return sketch.build_arrow(s, spec) if engine == "arrow" else sketch.build(s, spec)

    return run


SKETCHED = "SELECT a.level, y, emitted FROM (SELECT level, median(f2) AS y FROM (SELECT level, row, CAST(sum(counter * counter) AS DOUBLE) AS f2 FROM k WHERE row >= 0 GROUP BY 1, 2) GROUP BY level) a JOIN (SELECT level, counter AS emitted FROM k WHERE row = -1) b USING (level)"
add("sketch_counters_orders5", built(ORDERS5, MD5), counter_sql(ORDERS5, MD5) + " SELECT * FROM k")
add("sketch_counters_arrow_orders5", built(ORDERS5, MD5, "arrow"), counter_sql(ORDERS5, MD5) + " SELECT * FROM k")
add("sketch_moment_fast_orders5", lambda sp, sf: sketch.second_moment(built(ORDERS5, MD5)(sp, sf), MD5), counter_sql(ORDERS5, MD5) + " " + SKETCHED)
_plain = EstimatorSpec(s=5, fingerprint="md5_60", kind="plain", width=4, depth=3)


def plain_sql(w: W.Workload, spec: EstimatorSpec) -> str:
    parts = []
    for j in range(spec.width * spec.depth):
        s = hashing.tab4_sql(hashing.coefficients(spec.seed, j, "plain"), "fp")
        parts.append(f"SELECT level, {j // spec.width} AS row, {j} AS j, sum(CASE WHEN {s} & 1 = 1 THEN 1 ELSE -1 END) AS c FROM v GROUP BY 1, 2, 3")
    return f"{drawn_sql(w, spec)} SELECT level, median(f2) AS y, (SELECT count(*) FROM v WHERE v.level = q.level) AS emitted FROM (SELECT level, row, CAST(sum(c * c) AS DOUBLE) / {spec.width} AS f2 FROM ({' UNION ALL '.join(parts)}) GROUP BY 1, 2) q GROUP BY level"


add("sketch_moment_plain_orders5", lambda sp, sf: sketch.second_moment(built(ORDERS5, _plain)(sp, sf), _plain), plain_sql(ORDERS5, _plain))
for _n in ("orders5", "events5"):
    _w = W.TABLES[_n]
    add(f"sketch_profile_{_n}", lambda sp, sf, w=_w: shaped(estimate.self_join_size(w.frame(sp, sf), w.cols, MD5, "sketch", "rid")), counter_sql(_w, MD5) + solved_sql(_w.d, 3, SKETCHED))
DOCS6, _c6 = Source(W.shingle_sql(), 6), [f"a{i}" for i in range(1, 7)]
_half = MD5.with_(ratio=0.5)
add("sketch_profile_doc_shingles6", lambda sp, sf: shaped(estimate.self_join_size(W.shingle_frame(sp, sf), _c6, _half, "sketch", "rid")), counter_sql(DOCS6, _half) + solved_sql(6, 3, SKETCHED, factor="4"))
add("sketch_reliable_orders5", lambda sp, sf: longs(estimate.sanity(estimate.self_join_size(ORDERS5.frame(sp, sf), ORDERS5.cols, MD5, "sketch", "rid"), 5, MD5), "x").select(F.col("level").cast("long").alias("level"), "x", F.round("noise", 6).alias("noise"), "reliable"),
    f"SELECT level, x, round(y * sqrt(2.0 / {MD5.width}), 6) AS noise, x >= 2 * y * sqrt(2.0 / {MD5.width}) AS reliable FROM ({counter_sql(ORDERS5, MD5) + solved_sql(5, 3, SKETCHED)})")


def merged_by_year(spark: SparkSession, sf_dir: str) -> DataFrame:
    f = ORDERS5.frame(spark, sf_dir)
    early, late = (sketch.build(subvalues.level_stream(f.where(c), ORDERS5.cols, MD5, "rid"), MD5) for c in ("a4 < 1995", "a4 >= 1995"))
    return sketch.merge(early, late)


add("sketch_merge_by_year", merged_by_year, counter_sql(ORDERS5, MD5) + " SELECT * FROM k")

# ---- joins ----------------------------------------------------------------------------------


def join_sql(a: str, b: str, d: int, s: int = 1) -> str:
    parts = []
    for m in lattice.masks(d, s):
        cols = cols_of(d, m)
        on = " AND ".join(f"p.{c} IS NOT DISTINCT FROM q.{c}" for c in cols)
        grp = ", ".join(cols)
        parts.append(f"SELECT {m.bit_count()} AS level, coalesce(sum(p.c * q.c), 0) AS y FROM (SELECT {grp}, count(*) AS c FROM ta GROUP BY ALL) p JOIN (SELECT {grp}, count(*) AS c FROM tb GROUP BY ALL) q ON {on}")
    coef = ", ".join(f"({k}, {j}, {c})" for k, j, c in lattice.inversion_matrix(d, s))
    return f"""WITH ta AS ({a}), tb AS ({b}), lv AS (SELECT level, sum(y) AS y FROM ({' UNION ALL '.join(parts)}) GROUP BY level),
cf(k, level, coef) AS (VALUES {coef}), xs AS (SELECT k AS level, sum(coef * y) AS x FROM cf JOIN lv USING (level) GROUP BY k)
SELECT CAST(level AS BIGINT) AS level, CAST(y AS BIGINT) AS y, CAST(x AS BIGINT) AS x, CAST(sum(x) OVER (ORDER BY level DESC) AS BIGINT) AS pairs_at_least,
  round(CAST(sum(x) OVER (ORDER BY level DESC) AS DOUBLE) / (CAST((SELECT count(*) FROM ta) AS DOUBLE) * (SELECT count(*) FROM tb)), 9) AS selectivity FROM lv JOIN xs USING (level)"""


def joined(a: Callable, b: Callable, d: int, engine: str = "group", mode: str = "exact", spec: EstimatorSpec | None = None) -> Query:
    cols = [f"a{i + 1}" for i in range(d)]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        out = estimate.join_size(a(spark, sf_dir), b(spark, sf_dir), cols, cols, spec or EstimatorSpec(s=1), mode, "rid", "rid", engine)
        return longs(out, "y", "x", "pairs_at_least").select(F.col("level").cast("long").alias("level"), "y", "x", "pairs_at_least", F.round("selectivity", 9).alias("selectivity"))

    return run


def half(w: W.Workload, where: str) -> Callable:
    return lambda sp, sf: w.frame(sp, sf).where(where)


_even, _odd = "rid % 2 = 0", "rid % 2 = 1"
_ev = W.TABLES["events5"]
add("join_profile_orders_even_odd", joined(half(ORDERS5, _even), half(ORDERS5, _odd), 5), join_sql(f"SELECT * FROM ({ORDERS5.sql()}) WHERE {_even}", f"SELECT * FROM ({ORDERS5.sql()}) WHERE {_odd}", 5))
add("join_engine_equijoin", joined(half(ORDERS5, _even), half(ORDERS5, _odd), 5, "join"), ORACLES["join_profile_orders_even_odd"])
add("join_profile_events_even_odd", joined(half(_ev, "a1 % 2 = 0"), half(_ev, "a1 % 2 = 1"), 5), join_sql(f"SELECT * FROM ({_ev.sql()}) WHERE a1 % 2 = 0", f"SELECT * FROM ({_ev.sql()}) WHERE a1 % 2 = 1", 5))
add("join_profile_docs_benchmark", joined(W.shingle_frame, partial(W.shingle_frame, table="benchmark", rid="item_id"), 6), join_sql(W.shingle_sql(), W.shingle_sql("benchmark", "item_id"), 6))
_cust = W.Workload("customer2", "customer", "c_custkey", ("cast(c_nationkey as bigint)", "cast(floor(c_acctbal / 1000) as bigint)"))
_supp = W.Workload("supplier2", "supplier", "s_suppkey", ("cast(s_nationkey as bigint)", "cast(floor(s_acctbal / 1000) as bigint)"))
add("join_profile_customer_supplier", joined(_cust.frame, _supp.frame, 2), join_sql(_cust.sql(), _supp.sql(), 2))


def join_solved_sql(d: int, s: int, levels: str, na: str, nb: str, factor: str = "1") -> str:
    """The profile of a join from CTEs that end with ``levels`` (level, y)."""
    coef = ", ".join(f"({k}, {j}, {c})" for k, j, c in lattice.inversion_matrix(d, s))
    every = ", ".join(f"({k})" for k in range(s, d + 1))
    return f""", l0(level) AS (VALUES {every}), lv AS (SELECT level, coalesce(y, 0) AS y FROM l0 LEFT JOIN ({levels}) USING (level)),
cf(k, level, coef) AS (VALUES {coef}), xs AS (SELECT k AS level, sum(coef * y * {factor}) AS x FROM cf JOIN lv USING (level) GROUP BY k)
SELECT CAST(level AS BIGINT) AS level, CAST(round(y) AS BIGINT) AS y, CAST(round(x) AS BIGINT) AS x, CAST(round(sum(x) OVER (ORDER BY level DESC)) AS BIGINT) AS pairs_at_least,
  round(CAST(sum(x) OVER (ORDER BY level DESC) AS DOUBLE) / (CAST({na} AS DOUBLE) * {nb}), 9) AS selectivity FROM lv JOIN xs USING (level)"""


PRODUCT = "SELECT level, median(f2) AS y FROM (SELECT level, row, CAST(coalesce(sum(l.counter * r.counter), 0) AS DOUBLE) AS f2 FROM (SELECT * FROM ka WHERE row >= 0) l LEFT JOIN kb r USING (level, row, bucket) GROUP BY 1, 2) GROUP BY level"


def sketch_join_sql(a: Source, b: Source, spec: EstimatorSpec) -> str:
    return f"{counter_sql(a, spec, 'a')}, {counter_sql(b, spec, 'b')[5:]}" + join_solved_sql(a.d, spec.s, PRODUCT, "(SELECT count(*) FROM ta)", "(SELECT count(*) FROM tb)")


def parts_of(w: W.Workload, *wheres: str) -> tuple[Source, ...]:
    return tuple(Source(f"SELECT * FROM ({w.sql()}) WHERE {x}", w.d) for x in wheres)


_users = ("a1 % 2 = 0", "a1 % 2 = 1")
add("sketch_join_orders", joined(half(ORDERS5, _even), half(ORDERS5, _odd), 5, mode="sketch", spec=MD5), sketch_join_sql(*parts_of(ORDERS5, _even, _odd), MD5))
add("sketch_join_events", joined(half(_ev, _users[0]), half(_ev, _users[1]), 5, mode="sketch", spec=MD5), sketch_join_sql(*parts_of(_ev, *_users), MD5))


def sampled_join_sql(a: Source, b: Source, sa: EstimatorSpec, sb: EstimatorSpec) -> str:
    count = lambda p: f"(SELECT level, mask, fp, count(*) AS c FROM v{p} GROUP BY 1, 2, 3)"
    levels = f"SELECT level, CAST(sum(l.c * r.c) AS DOUBLE) AS y FROM {count('a')} l JOIN {count('b')} r USING (level, mask, fp) GROUP BY level"
    return f"{drawn_sql(a, sa, 'a')}, {drawn_sql(b, sb, 'b')[5:]}" + join_solved_sql(a.d, sa.s, levels, "(SELECT count(*) FROM ta)", "(SELECT count(*) FROM tb)", repr(1 / (sa.ratio * sb.ratio)))


def sampled_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two relations drawn at unequal ratios."""
    a, b = half(ORDERS5, _even)(spark, sf_dir), half(ORDERS5, _odd)(spark, sf_dir)
    out = estimate.join_size(a, b, ORDERS5.cols, ORDERS5.cols, _half, "exact", "rid", "rid", ratio_b=0.75)
    return longs(out, "y", "x", "pairs_at_least").select(F.col("level").cast("long").alias("level"), "y", "x", "pairs_at_least", F.round("selectivity", 9).alias("selectivity"))


add("join_sampled_orders", sampled_join, sampled_join_sql(*parts_of(ORDERS5, _even, _odd), _half, _half.with_(ratio=0.75, seed=8)))


def join_variance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bound of the variance of each level of a sketched join, from the self-join sizes of both sides."""
    y = [{r["level"]: float(r["y"]) for r in moments.level_moments(subvalues.level_stream(half(ORDERS5, x)(spark, sf_dir), ORDERS5.cols, EstimatorSpec(s=3), "rid")).collect()} for x in (_even, _odd)]
    var = bounds.variance_join({k: bounds.variance_inner_product(y[0][k], y[1][k], 1000) for k in y[0]}, 5, 3)
    return spark.createDataFrame([(k, float(round(v))) for k, v in var.items()], "level int, variance double")


def join_variance_sql() -> str:
    a, b = (f"(WITH t AS ({x.sql()}) {level_sql(5, 3)})" for x in parts_of(ORDERS5, _even, _odd))
    return f"""WITH y AS (SELECT level, 2 * CAST(a.y AS DOUBLE) * b.y / 1000 AS v FROM {a} a JOIN {b} b USING (level)),
w AS (SELECT max(v) FILTER (level = 5) AS v5, max(v) FILTER (level = 4) + 25 * max(v) FILTER (level = 5) AS v4, max(v) FILTER (level = 3) AS y3 FROM y)
SELECT unnest([5, 4, 3]) AS level, round(unnest([v5, v4, y3 + 16 * v4 + 100 * v5])) AS variance FROM w"""


add("join_variance_orders", join_variance, join_variance_sql())
add("half_sum_bound_orders", lambda sp, sf: baselines.half_sum_bound(half(ORDERS5, _even)(sp, sf), half(ORDERS5, _odd)(sp, sf), ORDERS5.cols, 4),
    f"""SELECT (a.g + b.g) / 2.0::DOUBLE AS bound, CAST(j.pairs_at_least AS DOUBLE) AS join_size FROM
    (SELECT g FROM ({profile_sql(f'SELECT * FROM ({ORDERS5.sql()}) WHERE {_even}', 5, 4)}) WHERE level = 4) a, (SELECT g FROM ({profile_sql(f'SELECT * FROM ({ORDERS5.sql()}) WHERE {_odd}', 5, 4)}) WHERE level = 4) b,
    (SELECT pairs_at_least FROM ({join_sql(f'SELECT * FROM ({ORDERS5.sql()}) WHERE {_even}', f'SELECT * FROM ({ORDERS5.sql()}) WHERE {_odd}', 5, 4)}) WHERE level = 4) j""")  # fmt: skip

# ---- baselines ------------------------------------------------------------------------------


def sampling_sql(w: W.Workload, s: int, size: int | str, seed: int = 7, never: bool = False) -> str:
    same = " + ".join(f"CAST(coalesce(l.a{i} = r.a{i}, false) AS INT)" if never else f"CAST(l.a{i} IS NOT DISTINCT FROM r.a{i} AS INT)" for i in range(1, w.d + 1))
    levels = ", ".join(f"({k})" for k in range(s, w.d + 1))
    return f"""WITH t AS ({w.sql()}), nn AS (SELECT count(*) AS n FROM t),
sm AS (SELECT * FROM t ORDER BY ('0x' || substr(md5('p{seed}|' || CAST(rid AS VARCHAR)), 1, 15))::BIGINT, rid LIMIT {size}), ss AS (SELECT count(*) AS m FROM sm),
p AS (SELECT {same} AS level, 2 * count(*) AS x FROM sm l JOIN sm r ON l.rid < r.rid GROUP BY 1), lv(level) AS (VALUES {levels}),
x AS (SELECT lv.level, coalesce(p.x, 0) * (CAST(n AS DOUBLE) * (n - 1) / (CAST(m AS DOUBLE) * (m - 1))) AS x, n, m FROM lv LEFT JOIN p USING (level), nn, ss)
SELECT CAST(level AS BIGINT) AS level, CAST(round(x) AS BIGINT) AS x, CAST(round(sum(x) OVER (ORDER BY level DESC) + n) AS BIGINT) AS g, n, m AS sample FROM x"""


for _n, _e in (("orders5", "pairs"), ("events5", "pairs"), ("orders6", "lattice")):
    _w = W.TABLES[_n]
    add(f"pair_sampling_{_n}", lambda sp, sf, w=_w, e=_e: longs(baselines.pair_sampling(w.frame(sp, sf), w.cols, EstimatorSpec(s=3), "rid", size=1000, engine=e, oracle=True), "x", "g").withColumn("level", F.col("level").cast("long")), sampling_sql(_w, 3, 1000))


for _e in ("pairs", "lattice"):
    add(f"pair_sampling_nulls_never_{_e}", lambda sp, sf, e=_e: longs(baselines.pair_sampling(_nulls.frame(sp, sf), _nulls.cols, EstimatorSpec(s=1, null_policy="never"), "rid", size=500, engine=e, oracle=True), "x", "g").withColumn("level", F.col("level").cast("long")), sampling_sql(_nulls, 1, 500, never=True))
_bytes = " + ".join(f"coalesce(octet_length(encode(CAST(a{i + 1} AS VARCHAR))), 0)" for i in range(5))
add("pair_sampling_bytes_orders5", lambda sp, sf: longs(baselines.pair_sampling(ORDERS5.frame(sp, sf), ORDERS5.cols, EstimatorSpec(s=3), "rid", bytes=12_000, oracle=True), "x", "g").withColumn("level", F.col("level").cast("long")),
    sampling_sql(ORDERS5, 3, f"(SELECT CAST(floor(12000 / avg({_bytes})) AS BIGINT) FROM t)"))


def pattern_sql(w: W.Workload, s: int, support: int) -> str:
    parts = [f"SELECT {m.bit_count()} AS level, c FROM (SELECT count(*) AS c FROM t GROUP BY {', '.join(cols_of(w.d, m))}) WHERE c >= {support}" for m in lattice.masks(w.d, s)]
    levels = ", ".join(f"({k})" for k in range(s, w.d + 1))
    return f"WITH t AS ({w.sql()}), f AS ({' UNION ALL '.join(parts)}), lv(level) AS (VALUES {levels}), per AS (SELECT lv.level, count(c) AS patterns, CAST(coalesce(sum(c * (c - 1)), 0) AS DOUBLE) AS pair_sum FROM lv LEFT JOIN f USING (level) GROUP BY 1)"


def pattern_lattice_sql(w: W.Workload, s: int, support: int) -> str:
    coef = ", ".join(f"({k}, {j}, {c})" for k, j, c in lattice.inversion_matrix(w.d, s))
    return pattern_sql(w, s, support) + f", cf(k, level, coef) AS (VALUES {coef}) SELECT level, patterns, pair_sum, x FROM per JOIN (SELECT k AS level, sum(coef * pair_sum) AS x FROM cf JOIN per USING (level) GROUP BY k) USING (level)"


def patterned(miner: str = "partition", overlap: str = "lattice", tail: str = "none", support: int = 4) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        out = baselines.signature_patterns(ORDERS5.frame(spark, sf_dir), ORDERS5.cols, 3, support, miner, overlap, tail, "rid", oracle=True)
        return out.select("level", "patterns", F.round("pair_sum", 3).alias("pair_sum"), F.round("x", 3).alias("x"))

    return run


def tail_sql(w: W.Workload, s: int, support: int) -> str:
    coef = ", ".join(f"({k}, {j}, {c})" for k, j, c in lattice.inversion_matrix(w.d, s))
    return pattern_sql(w, s, support) + f""", fq AS (SELECT level, c, count(*) AS m FROM f GROUP BY 1, 2),
ln AS (SELECT level, regr_slope(ln(m), ln(c)) AS b, regr_intercept(ln(m), ln(c)) AS a FROM fq GROUP BY level HAVING count(*) > 1),
tl AS (SELECT level, sum(exp(a + b * ln(f)) * f * (f - 1)) AS tail FROM ln, range(2, {support}) r(f) GROUP BY level),
pt AS (SELECT level, patterns, pair_sum + coalesce(tail, 0) AS pair_sum FROM per LEFT JOIN tl USING (level)), cf(k, level, coef) AS (VALUES {coef})
SELECT level, patterns, round(pair_sum, 3) AS pair_sum, round(x, 3) AS x FROM pt JOIN (SELECT k AS level, sum(coef * pair_sum) AS x FROM cf JOIN pt USING (level) GROUP BY k) USING (level)"""


def mined_sql(w: W.Workload, s: int, frequent: Callable[[str], str]) -> str:
    """Patterns of a miner: ``frequent`` makes (c) from the columns of a pattern."""
    parts = [f"SELECT {m.bit_count()} AS level, c FROM ({frequent(', '.join(cols_of(w.d, m)))})" for m in lattice.masks(w.d, s)]
    levels = ", ".join(f"({k})" for k in range(s, w.d + 1))
    return f"""WITH t AS ({w.sql()}), q AS (SELECT *, {digest_sql("'part|' || CAST(rid AS VARCHAR)")} % 8 AS part, {digest_sql("'sample|' || CAST(rid AS VARCHAR)")} % 1000 AS draw FROM t),
hd AS (SELECT part, count(*) AS held, (SELECT count(*) FROM t) AS n FROM q GROUP BY part), f AS ({' UNION ALL '.join(parts)}), lv(level) AS (VALUES {levels})
SELECT lv.level, count(c) AS patterns, CAST(coalesce(sum(c * (c - 1)), 0) AS DOUBLE) AS pair_sum, CAST(coalesce(sum(c * (c - 1)), 0) AS DOUBLE) AS x FROM lv LEFT JOIN f USING (level) GROUP BY 1"""


add("signature_patterns_orders5_none", patterned(overlap="none"), pattern_sql(ORDERS5, 3, 4) + " SELECT *, pair_sum AS x FROM per")
add("signature_patterns_orders5_lattice", patterned(), pattern_lattice_sql(ORDERS5, 3, 4))
add("signature_patterns_orders5_powerlaw", patterned(tail="powerlaw", support=6), tail_sql(ORDERS5, 3, 6))
add("signature_patterns_orders5_sample", patterned("sample", "none"), mined_sql(ORDERS5, 3, lambda cols: f"SELECT count(*) AS c FROM q GROUP BY {cols} HAVING count(*) >= 4 AND count(*) FILTER (draw < 100) >= 1"))
add("signature_patterns_orders5_lossy", patterned("lossy", "none"), mined_sql(ORDERS5, 3, lambda cols: f"SELECT CAST(sum(c) AS BIGINT) AS c FROM (SELECT {cols}, part, count(*) AS c FROM q GROUP BY ALL) JOIN hd USING (part) WHERE c * n > 2.0 * held GROUP BY {cols} HAVING sum(c) >= 2"))
_bag = W.Workload("customer3_bag", "customer", "c_custkey", W.TABLES["customer3"].attrs)
for _m in ("levelwise", "partition"):
    add(f"signature_patterns_repeated_rows_{_m}", lambda sp, sf, m=_m: baselines.patterns(_bag.frame(sp, sf).drop("rid"), _bag.cols, 1, 3, m).groupBy("level").agg(F.count(F.lit(1)).alias("patterns"), F.sum("c").alias("matches")),
        pattern_sql(_bag, 1, 3) + " SELECT level, count(*) AS patterns, CAST(sum(c) AS BIGINT) AS matches FROM f GROUP BY level")


def levelwise(spark: SparkSession, sf_dir: str) -> DataFrame:
    f = ORDERS5.frame(spark, sf_dir)
    return baselines.patterns(f, ORDERS5.cols, 3, 4, "levelwise", record_id="rid").groupBy("level").agg(F.count(F.lit(1)).alias("patterns"), F.sum("c").alias("matches"))


add("signature_patterns_orders5_levelwise", levelwise, pattern_sql(ORDERS5, 3, 4) + " SELECT level, count(*) AS patterns, CAST(sum(c) AS BIGINT) AS matches FROM f GROUP BY level")


def patterns_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Frequent patterns of two halves of orders: shared by both, and of the first only."""
    a, b = (baselines.patterns(half(ORDERS5, w)(spark, sf_dir), ORDERS5.cols, 4, 3, record_id="rid").select("mask", "fp") for w in (_even, _odd))
    tag = lambda df, name: df.groupBy("mask").agg(F.count(F.lit(1)).alias("patterns")).withColumn("part", F.lit(name))
    return tag(a.intersectAll(b), "shared").unionByName(tag(a.exceptAll(b), "first only"))


def patterns_sets_sql() -> str:
    side = lambda x: " UNION ALL ".join(f"SELECT {m} AS mask, {' || '.join(encoded_sql(c) for c in cols_of(5, m))} AS text FROM ({x.sql()}) GROUP BY ALL HAVING count(*) >= 3" for m in lattice.masks(5, 4))
    a, b = parts_of(ORDERS5, _even, _odd)
    return f"""WITH a AS ({side(a)}), b AS ({side(b)})
SELECT mask, count(*) AS patterns, 'shared' AS part FROM (FROM a INTERSECT ALL FROM b) GROUP BY mask UNION ALL SELECT mask, count(*) AS patterns, 'first only' AS part FROM (FROM a EXCEPT ALL FROM b) GROUP BY mask"""


add("patterns_intersect_except", patterns_sets, patterns_sets_sql())


def strata_sql(w: W.Workload) -> str:
    cols = ", ".join(f"a{i}" for i in baselines.chosen_columns(w.d, None, 7))
    return f"WITH t AS ({w.sql()}), b AS (SELECT count(*) AS b FROM t GROUP BY {cols}) SELECT count(*) AS buckets, CAST(sum(b) AS BIGINT) AS n, CAST(sum(b * (b - 1) // 2) AS BIGINT) AS pairs_high, CAST(sum(b) * (sum(b) - 1) // 2 - sum(b * (b - 1) // 2) AS BIGINT) AS pairs_low FROM b"


def bucket_strata(spark: SparkSession, sf_dir: str) -> DataFrame:
    b = baselines.lsh_buckets(ORDERS5.frame(spark, sf_dir), ORDERS5.cols, "rid").groupBy("bucket").agg(F.count(F.lit(1)).alias("b"))
    got = b.agg(F.count("b").alias("buckets"), F.sum("b").alias("n"), F.sum((F.col("b") * (F.col("b") - 1) / 2).cast("long")).alias("pairs_high"))
    return got.withColumn("pairs_low", (F.col("n") * (F.col("n") - 1) / 2 - F.col("pairs_high")).cast("long"))


add("lsh_bucket_strata_orders5", bucket_strata, strata_sql(ORDERS5))


def stratified(w: W.Workload, spec: EstimatorSpec, **kw) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        out = baselines.lsh_strata(w.frame(spark, sf_dir), w.cols, spec, "rid", oracle=True, **kw)
        return longs(out, "x", "g").withColumn("level", F.col("level").cast("long"))

    return run


def stratified_sql(w: W.Workload, spec: EstimatorSpec, policy: str = "linear", fraction: float = 0.005, adaptive: bool = False) -> str:
    bucket = "concat_ws('|', " + ", ".join(f"coalesce(CAST(a{i} AS VARCHAR), '~')" for i in baselines.chosen_columns(w.d, None, spec.seed)) + ")"
    share = lambda c: "n" if policy == "linear" else f"greatest(1, CAST(round({fraction} * {c}) AS BIGINT))"
    same = " + ".join(f"CAST(l.a{i} IS NOT DISTINCT FROM r.a{i} AS INT)" for i in range(1, w.d + 1))
    levels = ", ".join(f"({k})" for k in range(spec.s, w.d + 1))
    at = lambda what, total: f"{digest_sql(f"'{what}{spec.seed}|' || CAST(id AS VARCHAR)")} % {total}"
    one = lambda what: f"SELECT id, bucket, at_ - start AS k FROM (SELECT id, {at(what, 'n')} AS at_ FROM il, tt) p ASOF JOIN st ON p.at_ >= st.start"
    hits = lambda ends: f"SELECT {same} AS level, count(*) AS hits FROM ({ends}) e JOIN o l ON l.bucket = e.lb AND l.k = e.lk JOIN o r ON r.bucket = e.rb AND r.k = e.rk GROUP BY 1"
    scale = f"CASE WHEN (SELECT coalesce(sum(hits), 0) FROM hl WHERE level >= {spec.s}) < greatest(1, ceil(log2(n))) THEN 1.0 ELSE low / (SELECT CAST(sum(hits) AS DOUBLE) FROM hl) END" if adaptive else "low / (SELECT CAST(sum(hits) AS DOUBLE) FROM hl)"
    return f"""WITH t AS ({w.sql()}), kk AS (SELECT *, {digest_sql(bucket)} AS bucket, {digest_sql("'o|' || CAST(rid AS VARCHAR)")} AS h FROM t),
o AS (SELECT *, row_number() OVER (PARTITION BY bucket ORDER BY h, rid) - 1 AS k FROM kk), sz AS (SELECT bucket, count(*) AS b FROM kk GROUP BY 1),
st AS (SELECT bucket, b, b * (b - 1) // 2 AS pairs, CAST(sum(b) OVER w - b AS BIGINT) AS start, CAST(sum(b * (b - 1) // 2) OVER w - b * (b - 1) // 2 AS BIGINT) AS pair_start FROM sz WINDOW w AS (ORDER BY bucket ROWS UNBOUNDED PRECEDING)),
t0 AS (SELECT CAST(sum(b) AS BIGINT) AS n, CAST(sum(pairs) AS BIGINT) AS high FROM st), tt AS (SELECT n, high, n * (n - 1) // 2 - high AS low FROM t0),
ih AS (SELECT unnest(range({share('high')})) AS id FROM tt), il AS (SELECT unnest(range(CAST(ceil(CAST({share('low')} AS DOUBLE) * n * n / (2 * low)) AS BIGINT))) AS id FROM tt),
p0 AS (SELECT bucket, at_ - pair_start AS o FROM (SELECT id, {at('h', 'high')} AS at_ FROM ih, tt) p ASOF JOIN (SELECT * FROM st WHERE pairs > 0) s ON p.at_ >= s.pair_start),
p1 AS (SELECT bucket, o, CAST(floor((sqrt(8.0 * o + 1) + 1) / 2) AS BIGINT) AS a FROM p0), p2 AS (SELECT bucket, o, CASE WHEN a * (a - 1) // 2 > o THEN a - 1 WHEN a * (a + 1) // 2 <= o THEN a + 1 ELSE a END AS a FROM p1),
hh AS ({hits("SELECT bucket AS lb, a AS lk, bucket AS rb, o - a * (a - 1) // 2 AS rk FROM p2")}),
hl AS ({hits(f"SELECT x.bucket AS lb, x.k AS lk, y.bucket AS rb, y.k AS rk FROM ({one('l')}) x JOIN ({one('r')}) y USING (id) WHERE x.bucket <> y.bucket")}),
al AS (SELECT level, 2.0 * hits * (high / (SELECT CAST(sum(hits) AS DOUBLE) FROM hh)) AS x FROM hh, tt UNION ALL SELECT level, 2.0 * hits * ({scale}) AS x FROM hl, tt),
lv(level) AS (VALUES {levels}), xs AS (SELECT lv.level, coalesce(sum(x), 0) AS x FROM lv LEFT JOIN al USING (level) GROUP BY 1)
SELECT CAST(level AS BIGINT) AS level, CAST(round(x) AS BIGINT) AS x, CAST(round(sum(x) OVER (ORDER BY level DESC) + n) AS BIGINT) AS g, n, high AS pairs_high, low AS pairs_low FROM xs, tt"""


for _n, _w, _spec, _kw in (("linear_orders5", ORDERS5, EstimatorSpec(s=3), {}), ("fraction_orders5", ORDERS5, EstimatorSpec(s=3), {"policy": "fraction"}), ("adaptive_orders6", W.TABLES["orders6"], EstimatorSpec(s=4), {"adaptive": True})):
    add(f"lsh_strata_{_n}", stratified(_w, _spec, **_kw), stratified_sql(_w, _spec, **_kw))


def asof_lookup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For a thousand ordinals spread over all orders, the customer whose run of orders holds it: an as-of join on running totals."""
    orders = table(spark, sf_dir, "orders")
    n = orders.count()
    size = orders.groupBy(F.xxhash64("o_custkey").alias("bucket"), "o_custkey").agg(F.count(F.lit(1)).alias("b"))
    size = size.select(F.col("o_custkey").alias("bucket"), "b", F.lit(0).cast("long").alias("pairs"), F.lit(0).alias("seed"))
    starts = baselines.running(size, 1, 64)
    asked = spark.range(0, 1000).select(F.lit(0).alias("seed"), F.floor(F.col("id") * n / 1000).cast("long").alias("at"))
    return baselines.located(asked, starts, "start", "b").select("at", "bucket", "start")


add("asof_bucket_lookup", asof_lookup, "WITH s AS (SELECT o_custkey AS bucket, count(*) AS b FROM orders GROUP BY 1), r AS (SELECT bucket, b, CAST(sum(b) OVER (ORDER BY bucket) - b AS BIGINT) AS start FROM s), q AS (SELECT unnest(range(1000)) * (SELECT count(*) FROM orders) // 1000 AS at_) SELECT at_ AS \"at\", bucket, start FROM q JOIN r ON at_ >= start AND at_ < start + b")

# ---- measures -------------------------------------------------------------------------------


SEEDS = range(1, 31)


def compared(frame: Callable[[SparkSession, str], DataFrame], d: int, spec: EstimatorSpec, methods: dict[str, Callable[[DataFrame, list[str]], DataFrame]], keep: bool = False) -> Query:
    """(method, level, runs, mean_error, std_error, mean_abs_error): relative errors of repeated estimates, made by each method from the records.

    ``keep``: the records cost much to make, so they are written for all methods and deleted at the end.
    """

    def kept(spark: SparkSession, sf_dir: str) -> DataFrame:
        folder = shared_path(spark, "records")
        try:
            frame(spark, sf_dir).write.parquet(f"{folder}/records")
            out = errors(spark, spark.read.parquet(f"{folder}/records"))
            return spark.createDataFrame(out.collect(), out.schema)  # a row for each method and level
        finally:
            measures.deleted(spark, folder)

    def errors(spark: SparkSession, f: DataFrame) -> DataFrame:
        cols, out = [f"a{i + 1}" for i in range(d)], None
        true = estimate.self_join_size(f, cols, EstimatorSpec(s=spec.s), "exact", "rid")
        for name, one in methods.items():
            got = measures.relative_error(one(f, cols).select("seed", "level", F.col("g").cast("double").alias("g")), true).withColumn("method", F.lit(name))
            out = got if out is None else out.unionByName(got)
        return measures.summary(out, "method")

    return kept if keep else lambda spark, sf_dir: errors(spark, frame(spark, sf_dir))


def lattice_runs(spec: EstimatorSpec, mode: str, seeds: range = SEEDS) -> Callable:
    return lambda f, cols: estimate.repeated(f, cols, spec, "rid", seeds, mode)


def strata_runs(spec: EstimatorSpec, seeds: range = SEEDS, **kw) -> Callable:
    return lambda f, cols: baselines.lsh_strata(f, cols, spec, "rid", seeds=seeds, **kw)


def sampling_runs(spec: EstimatorSpec, seeds: range = SEEDS, **kw) -> Callable:
    return lambda f, cols: baselines.pair_sampling(f, cols, spec, "rid", engine="lattice", seeds=seeds, **kw)


def shingles(features: int = 6, table: str = "documents", rid: str = "doc_id") -> Callable[[SparkSession, str], DataFrame]:
    return partial(W.shingle_frame, table=table, rid=rid, features=features, oracle=False)


_h3 = EstimatorSpec(s=3, ratio=0.5)
add("relative_error_summary", compared(ORDERS5.frame, 5, _h3, {"lattice exact": lattice_runs(_h3, "exact"), "lattice sketch": lattice_runs(_h3, "sketch"), "pair sampling": sampling_runs(_h3, size=1000)}))
# exact moments against LSH strata: 30 runs, half of the sub-values, as many pairs of each stratum as records
for _n, _f, _d in (("orders5", ORDERS5.frame, 5), ("orders6", W.TABLES["orders6"].frame, 6), ("doc_shingles6", shingles(), 6)):
    add(f"exact_vs_strata_{_n}", compared(_f, _d, _h3, {"lattice exact": lattice_runs(_h3, "exact"), "lsh strata": strata_runs(_h3)}, keep=_n == "doc_shingles6"))
# the policy that draws a constant share of all pairs is quadratic: 10 runs
add("exact_vs_strata_fraction_orders5", compared(ORDERS5.frame, 5, _h3, {"lattice exact": lattice_runs(_h3, "exact", range(1, 11)), "lsh strata": strata_runs(_h3, range(1, 11), policy="fraction")}))
# sketches of s levels x 3 x 1000 counters of 4 bytes against a sample of as many bytes
for _n, _f in (("orders6", W.TABLES["orders6"].frame), ("doc_shingles6", shingles())):
    add(f"equal_space_{_n}", compared(_f, 6, _h3, {"lattice sketch": lattice_runs(_h3, "sketch"), "pair sampling": sampling_runs(_h3, bytes=bounds.sketch_bytes(6, 3, 1000, 3))}))


def swept(settings: list[tuple[str, Callable[[SparkSession, str], DataFrame], int, EstimatorSpec]], seeds: range = SEEDS) -> Query:
    """Spread of the sketch's error as one parameter moves."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        out = None
        for name, frame, d, spec in settings:
            got = compared(frame, d, spec, {name: lattice_runs(spec, "sketch", seeds)})(spark, sf_dir).withColumnRenamed("method", "setting")
            out = got if out is None else out.unionByName(got)
        return out

    return run


def resized(frame: Callable, times: float) -> Callable:
    """The table ``times`` over, or half of it by a hash of its key."""
    return (lambda sp, sf: frame(sp, sf).where(F.pmod(F.xxhash64("rid"), F.lit(2)) == 0)) if times < 1 else (lambda sp, sf: W.duplicated(frame(sp, sf), int(times)))


add("ablation_ratio_shingles", swept([(f"r={r}", shingles(), 6, EstimatorSpec(s=1, ratio=r)) for r in (0.25, 0.5, 0.75, 1.0)]))
add("ablation_ratio_orders5", swept([(f"r={r}", ORDERS5.frame, 5, EstimatorSpec(s=1, ratio=r)) for r in (0.25, 0.5, 0.75, 1.0)]))
add("ablation_dimension_shingles", swept([(f"d={d}", shingles(d), d, EstimatorSpec(s=d - 2, ratio=0.5)) for d in (4, 5, 6, 7, 8)]))
add("ablation_dimension_embed", swept([(f"d={d}", W.TABLES["embed8"].frame, d, EstimatorSpec(s=d - 1, ratio=0.5)) for d in (4, 6, 8)]))
for _n, _f, _d in (("shingles", shingles(), 6), ("orders5", ORDERS5.frame, 5)):
    add("ablation_size_" + ("dup" if _n == "orders5" else _n), swept([(f"x{x:g}", resized(_f, x), _d, EstimatorSpec(s=3, ratio=0.5)) for x in (0.5, 1, 2, 4, 8)]))


def materialized(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes that several passes keep on disk, by threshold: level streams against buckets."""
    return measures.materialization(ORDERS5.frame(spark, sf_dir), ORDERS5.cols, EstimatorSpec(s=1, ratio=0.5), "rid", shared_path(spark, "levels"))


add("materialization_orders5", materialized)


def method_costs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(method, passes, summarize_s, calculate_s): what reads the data and what comes after."""
    f, spec, folder = ORDERS5.frame(spark, sf_dir), EstimatorSpec(s=3), shared_path(spark, "costs")
    n = f.count()
    _, built_s = measures.timed(lambda: sketch.save(sketch.build(subvalues.level_stream(f, ORDERS5.cols, spec, "rid", True), spec), f"{folder}/sketch"))
    _, solved_s = measures.timed(lambda: estimate.from_sketch(sketch.load(spark, f"{folder}/sketch"), 5, spec).collect())
    base = records.canonicalized(f, ORDERS5.cols, "rid")
    _, drawn_s = measures.timed(lambda: baselines.least(base, 1000, [7], False).write.parquet(f"{folder}/sample"))
    held = spark.read.parquet(f"{folder}/sample")
    _, pairs_s = measures.timed(lambda: baselines.all_pairs(held, ORDERS5.cols, "rid").collect())
    _, strata_s = measures.timed(lambda: baselines.lsh_strata(f, ORDERS5.cols, spec, "rid", sizes=(n, n)).collect())
    _, pattern_s = measures.timed(lambda: baselines.signature_patterns(f, ORDERS5.cols, 3, 4, record_id="rid").collect())
    measures.deleted(spark, folder)
    rows = [("lattice", built_s, solved_s), ("pair_sampling", drawn_s, pairs_s), ("lsh_strata", strata_s, 0.0), ("signature_partition", pattern_s, 0.0)]
    return spark.createDataFrame([(m, bounds.PASSES[m], a, b) for m, a, b in rows], "method string, passes int, summarize_s double, calculate_s double")


add("method_costs_orders5", method_costs)


def matching(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The least sample that reaches the spread of the sketch, and its exponent of n, on the skewed generated set."""
    g, spec = W.generated_pairs(spark, sf_dir, *W.GENERATED["pairs_20_80"]), EstimatorSpec(s=4)
    target = compared(lambda *_: g, 5, spec, {"sketch": lattice_runs(spec, "sketch", range(1, 11))})(spark, sf_dir).where("level = 4").first()["std_error"]
    n = g.count()
    size, exponent = measures.matching_sample(g, ORDERS5.cols, spec, "rid", target, range(1, 6), [max(2, n * k // 8) for k in (1, 2, 4, 6, 8)])
    return spark.createDataFrame([(n, float(target), size, float(exponent))], "n long, target_std double, size long, exponent double")


add("matching_sample_pairs_20_80", matching)
add("choose_attributes_orders5", lambda sp, sf: sp.createDataFrame([(i, a) for i, a in enumerate(choose_attributes(ORDERS5.frame(sp, sf), ORDERS5.cols, 3))], "place long, attribute string"),
    f"WITH t AS ({ORDERS5.sql()}), c AS ({' UNION ALL '.join(f"SELECT 'a{i + 1}' AS a, count(DISTINCT a{i + 1}) AS n FROM t" for i in range(5))}), k AS (SELECT a FROM c ORDER BY n DESC, a LIMIT 3) SELECT row_number() OVER (ORDER BY a) - 1 AS place, a AS attribute FROM k")


def orders_by_year(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(year, n): how many orders there are up to each year, the sizes through which the table grows."""
    per = table(spark, sf_dir, "orders").groupBy(F.year("o_orderdate").alias("year")).agg(F.count(F.lit(1)).alias("c"))
    return per.select("year", F.sum("c").over(Window.orderBy("year")).alias("n"))


YEARS = "(SELECT y AS year, CAST(sum(c) OVER (ORDER BY y) AS BIGINT) AS n FROM (SELECT year(o_orderdate) AS y, count(*) AS c FROM orders GROUP BY 1))"


def samples_by_year(spark: SparkSession, sf_dir: str) -> DataFrame:
    of = F.udf(lambda n: (bounds.min_sample_size(n), bounds.sample_exponent(n, 2), bounds.sample_exponent(n, 3)), "least long, p2 long, p3 long")
    return orders_by_year(spark, sf_dir).select("year", "n", of("n").alias("o")).select("year", "n", "o.*")


add("sample_sizes", samples_by_year,
    f"SELECT CAST(year AS INT) AS year, n, CAST(ceil(sqrt(n)) AS BIGINT) AS least, CAST(round(pow(n, 2 / 3)) AS BIGINT) AS p2, CAST(round(pow(n, 3 / 4)) AS BIGINT) AS p3 FROM {YEARS}")


def advised(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether to run a similarity join over the documents, from the estimated size."""
    rows = [r.asDict() for r in estimate.self_join_size(shingles()(spark, sf_dir), _c6, EstimatorSpec(s=4), "sketch", "rid").collect()]
    return spark.createDataFrame([(bounds.advise(rows, rows[0]["n"]),)], "advice string")


add("dedup_advice_docs", advised)
PARTS10 = W.Workload("parts10", "part", "p_partkey", (
    "split_part(p_name, ' ', 1)", "split_part(p_name, ' ', 2)", "p_brand", "p_type", "cast(floor(p_size / 10) as bigint)", "nullif(p_size % 10, 0)",
    *[f"cast(floor(p_retailprice / {k}) as bigint) % 10" for k in (1000, 100, 10, 1)],
))


def parts_by_width(dims: range) -> Query:
    """(d, n, distinct, g): of the first d attributes the records, the distinct vectors and the pairs that agree on all of them."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        f = PARTS10.frame(spark, sf_dir)
        of = [longs(moments.second_moment(f, PARTS10.cols[:d]), "f2").select(F.lit(d).alias("d"), "n", "distinct", F.col("f2").alias("g")) for d in dims]
        return reduce(DataFrame.unionByName, of)

    return run


def parts_by_width_sql(dims: range) -> str:
    one = [f"SELECT {d} AS d, CAST(sum(c) AS BIGINT) AS n, count(*) AS \"distinct\", CAST(sum(c * c) AS BIGINT) AS g FROM (SELECT count(*) AS c FROM ({PARTS10.sql()}) GROUP BY {', '.join(PARTS10.cols[:d])})" for d in dims]
    return f"({' UNION ALL '.join(one)})"


_dims = range(3, 11)


def parts_by_values(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(d, present, records): how many records have so many values, not null, among the first d attributes."""
    f = PARTS10.frame(spark, sf_dir)
    there = [F.when(F.col(c).isNotNull(), 1).otherwise(0) for c in PARTS10.cols]
    each = F.explode(F.array(*[F.struct(F.lit(d).alias("d"), sum(there[:d]).alias("present")) for d in _dims])).alias("e")
    return f.select(each).groupBy("e.d", "e.present").agg(F.count(F.lit(1)).alias("records"))


def parts_by_values_sql() -> str:
    return "(" + " UNION ALL ".join(f"SELECT {d} AS d, {' + '.join(f'CAST({c} IS NOT NULL AS INT)' for c in PARTS10.cols[:d])} AS present, count(*) AS records FROM ({PARTS10.sql()}) GROUP BY ALL" for d in _dims) + ")"


add("bound_grid_exact", lambda sp, sf: bounds.grid(parts_by_width(_dims)(sp, sf)).select(F.col("d").cast("long").alias("d"), F.col("s").cast("long").alias("s"), "g", F.round("exact", 6).alias("bound")),
    f"WITH RECURSIVE f(n, v) AS (SELECT 0, 1::HUGEINT UNION ALL SELECT n + 1, v * (n + 1) FROM f WHERE n < 20), g AS (SELECT CAST(d AS BIGINT) AS d, s, g FROM {parts_by_width_sql(_dims)} a, range(1, 11) b(s) WHERE s <= d) SELECT d, s, g, round(CAST(((SELECT v FROM f WHERE n = d) // ((SELECT v FROM f WHERE n = s) * (SELECT v FROM f WHERE n = d - s))) ** 2 * ((SELECT v FROM f WHERE n = 2 * (d - s)) // ((SELECT v FROM f WHERE n = d - s) ** 2)) AS DOUBLE) / g, 6) AS bound FROM g")
_spread = "pow(round(gamma(d + 1) / (gamma(s + 1) * gamma(d - s + 1))), 2) * round(gamma(2 * (d - s) + 1) / pow(gamma(d - s + 1), 2))"
add("bound_grid_sketch", lambda sp, sf: bounds.grid(parts_by_width(_dims)(sp, sf)).select("d", "s", "g", *[F.round(c, 6).alias(c) for c in ("exact", "sketch", "sketch_tenth")]),
    f"SELECT d, CAST(s AS INT) AS s, g, round(v / g, 6) AS exact, round(v * (1.002::DOUBLE / g + 0.002::DOUBLE), 6) AS sketch, round(v * 10 * (1.002::DOUBLE / g + 0.002::DOUBLE), 6) AS sketch_tenth FROM (SELECT d, s, g, {_spread} AS v FROM {parts_by_width_sql(_dims)} a, range(1, 11) b(s) WHERE s <= d)")
add("asymptotic_grid", lambda sp, sf: bounds.asymptotic_grid(orders_by_year(sp, sf)).select("n", "p", "s", "lattice", F.round("sampling").alias("sampling")),
    f"SELECT n, p, 6 - p AS s, CAST(n * CASE p WHEN 2 THEN 6 ELSE 16 END AS DOUBLE) AS lattice, round(pow(n, 2 * p / (p + 1))) AS sampling FROM {YEARS}, (VALUES (2), (3)) b(p)")
def drawn_by_budget(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(d, level, ratio, present, expected): the ratio at which no record emits over 20 sub-values of a level, those there are and those expected to be drawn."""
    rows = [(d, k, r, p, comb(p, k)) for d in (6, 8, 10) for k, r in bounds.ratio_for_budget(d, 2, 20).items() for p in range(d + 1)]
    of = spark.createDataFrame(rows, "d int, level int, ratio double, present int, each long")
    all_of = of.join(parts_by_values(spark, sf_dir), ["d", "present"]).groupBy("d", "level", "ratio").agg(F.sum(F.col("each") * F.col("records")).alias("present"))
    return all_of.withColumn("expected", F.round(F.col("ratio") * F.col("present"), 3))


add("ratio_for_budget", drawn_by_budget,
    f"WITH x AS (SELECT bit_count(CAST(x AS BIGINT)) AS k, x FROM range(1, 1024) b(x)), w AS (SELECT p, k, count(*) AS each FROM range(0, 11) a(p), x WHERE x < (1 << p) GROUP BY 1, 2), r AS (SELECT v.d, CAST(t.k AS INT) AS level, least(1.0, 20 / CAST(max(f.each) AS DOUBLE)) AS ratio, CAST(sum(v.records * coalesce(w.each, 0)) AS BIGINT) AS present FROM {parts_by_values_sql()} v JOIN range(2, 11) t(k) ON t.k <= v.d JOIN w f ON f.p = v.d AND f.k = t.k LEFT JOIN w ON w.p = v.present AND w.k = t.k WHERE v.d IN (6, 8, 10) GROUP BY 1, 2) SELECT *, round(ratio * present, 3) AS expected FROM r")
add("space_table", lambda sp, sf: measures.space_table(ORDERS5.frame(sp, sf), ORDERS5.cols, 3),
    f"SELECT 5 AS d, s, (6 - s) * 3000 * 4 AS bytes4, (6 - s) * 3000 * 8 AS bytes8, CAST(floor((6 - s) * 12000 / (SELECT avg({_bytes}) FROM ({ORDERS5.sql()}))) AS BIGINT) AS equal_sample FROM (VALUES (3), (4), (5)) v(s)")
def emitted_by_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(d, s, sub_values, emitted): sub-values of a record with d values, and what the records emit if nulls never agree."""
    of = spark.createDataFrame([(d, s, p, sub_values(d, s), sub_values(p, s)) for d in _dims for s in range(1, d + 1) for p in range(d + 1)], "d int, s int, present int, sub_values long, each long")
    return of.join(parts_by_values(spark, sf_dir), ["d", "present"]).groupBy("d", "s", "sub_values").agg(F.sum(F.col("each") * F.col("records")).alias("emitted"))


add("subvalues_per_record", emitted_by_table,
    f"WITH x AS (SELECT bit_count(CAST(x AS BIGINT)) AS k, x FROM range(1, 1024) b(x)), w AS (SELECT p, s, count(*) AS each FROM range(0, 11) a(p), range(1, 11) t(s), x WHERE x < (1 << p) AND k >= s GROUP BY 1, 2) SELECT v.d, CAST(t.s AS INT) AS s, max(f.each) AS sub_values, CAST(sum(v.records * coalesce(w.each, 0)) AS BIGINT) AS emitted FROM {parts_by_values_sql()} v JOIN range(1, 11) t(s) ON t.s <= v.d JOIN w f ON f.p = v.d AND f.s = t.s LEFT JOIN w ON w.p = v.present AND w.s = t.s GROUP BY 1, 2")
add("plan_sketch_size", lambda sp, sf: parts_by_width(range(3, 9))(sp, sf).join(sp.createDataFrame([(d, d - 1, *bounds.size_sketch(0.1, 0.05, d, d - 1)) for d in range(3, 9)], "d int, s int, width long, depth int"), "d")
    .select("d", "s", "width", "depth", "distinct", (F.col("width") * F.col("depth") < F.col("distinct")).alias("below_exact")),
    f"SELECT d, d - 1 AS s, width, 25 AS depth, \"distinct\", width * 25 < \"distinct\" AS below_exact FROM (SELECT *, CAST(ceil(8 * CAST(d * d * 2 AS DOUBLE) / (0.1::DOUBLE * 0.1::DOUBLE)) AS BIGINT) AS width FROM {parts_by_width_sql(range(3, 9))})")
EXAMPLE3 = W.Workload("example3", "orders", "o_orderkey", ("o_orderstatus", "o_orderpriority", "month(o_orderdate)"))
add("worked_example", exact(EXAMPLE3.frame, 3), profile_sql(EXAMPLE3.sql(), 3))


def counterexample_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The first order against the first ones that agree with it on exactly two of three fields, a different two each: the join exceeds half the sum of the self-joins."""
    t = EXAMPLE3.frame(spark, sf_dir)
    a = t.orderBy("rid").limit(1)
    mask = sum(F.when(F.col(f"l.a{i}").eqNullSafe(F.col(f"r.a{i}")), 1 << (i - 1)).otherwise(0) for i in (1, 2, 3))
    near = t.alias("l").crossJoin(F.broadcast(a.alias("r"))).select(mask.alias("mask"), F.struct("l.rid", "l.a1", "l.a2", "l.a3").alias("t"))
    b = near.where("mask in (3, 5, 6)").groupBy("mask").agg(F.min("t").alias("t")).select("mask", "t.*")
    out = [baselines.half_sum_bound(a, b.where(f"mask in {m}").drop("mask"), EXAMPLE3.cols, 2) for m in ("(3, 5)", "(3, 5, 6)")]
    return out[0].unionByName(out[1])


def counterexample_sql() -> str:
    same = lambda l, r: " + ".join(f"CAST({l}.a{i} IS NOT DISTINCT FROM {r}.a{i} AS INT)" for i in (1, 2, 3))
    mask = " + ".join(f"{1 << (i - 1)} * CAST(t.a{i} IS NOT DISTINCT FROM f.a{i} AS INT)" for i in (1, 2, 3))
    pairs = lambda x, y, m, w: f"(SELECT count(*) FROM {x} l, {y} r WHERE {same('l', 'r')} >= 2{''.join(f' AND {v}.mask IN {m}' for v in w)})"
    rows = [f"SELECT ({pairs('f', 'f', m, '')} + {pairs('b', 'b', m, 'lr')}) / 2::DOUBLE AS bound, CAST({pairs('f', 'b', m, 'r')} AS DOUBLE) AS join_size" for m in ("(3, 5)", "(3, 5, 6)")]
    return f"WITH t AS ({EXAMPLE3.sql()}), f AS (SELECT * FROM t ORDER BY rid LIMIT 1), k AS (SELECT t.*, {mask} AS mask FROM t, f), b AS (SELECT * FROM k WHERE mask IN (3, 5, 6) QUALIFY row_number() OVER (PARTITION BY mask ORDER BY rid) = 1) {' UNION ALL '.join(rows)}"


add("half_sum_counterexamples", counterexample_rows, counterexample_sql())

# ---- labels and shingles --------------------------------------------------------------------


def labelled_docs(how: str) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        good = table(spark, sf_dir, "labels").where("quality = 1 and toxic = 0").select(F.col("doc_id").alias("rid"))
        return W.shingle_frame(spark, sf_dir).join(good, "rid", how)

    return run


_good = "SELECT doc_id FROM labels WHERE quality = 1 AND toxic = 0"
add("label_semi_join_profile", exact(labelled_docs("left_semi"), 6, 4), profile_sql(f"SELECT * FROM ({W.shingle_sql()}) WHERE rid IN ({_good})", 6, 4))
add("label_anti_join_profile", exact(labelled_docs("left_anti"), 6, 4), profile_sql(f"SELECT * FROM ({W.shingle_sql()}) WHERE rid NOT IN ({_good})", 6, 4))
add("shingle_vectors_docs", W.shingle_frame, W.shingle_sql())
add("shingle_sizes_docs", lambda sp, sf: table(sp, sf, "documents").select("doc_id", F.size(shingle_set(F.col("text"))).cast("long").alias("shingles")),
    "SELECT doc_id, CAST(len(list_distinct(string_split_regex(trim(lower(text)), '\\s+'))) AS BIGINT) AS shingles FROM documents")

# ---- streams --------------------------------------------------------------------------------


def file_stream(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table as a stream, be it one file or a folder of them: a pattern of the path fits both."""
    schema = spark.read.parquet(f"{sf_dir}/{name}.parquet").schema
    return spark.readStream.schema(schema).load(f"{sf_dir}/{name}[.]parquet")


def events_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    return file_stream(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))


def event_attrs(df: DataFrame) -> DataFrame:
    return df.selectExpr("event_id AS rid", "ts", *[f"{e} AS a{i + 1}" for i, e in enumerate(W.EVENTS)])


def shared_path(spark: SparkSession, what: str) -> str:
    """A new folder below the one the cluster shares; only on one machine may that be unset."""
    shared = spark.conf.get("spark.checkpoint.dir", None)
    if not shared and not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all machines share")
    return f"{shared}/{what}-{uuid.uuid4().hex}" if shared else tempfile.mkdtemp(prefix=f"{what}-")


def drained(spark: SparkSession, df: DataFrame, mode: str) -> DataFrame:
    """The final table of a query that reads what is there and stops, written to the shared folder batch by batch."""
    folder, last = shared_path(spark, "stream"), {}

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/out/batch={number}")
        last["number"] = number

    q = df.writeStream.outputMode(mode).option("checkpointLocation", f"{folder}/state").foreachBatch(keep).trigger(availableNow=True).start()
    q.awaitTermination()
    if not last:
        return spark.createDataFrame([], df.schema)
    out = spark.read.schema(df.schema)
    return out.parquet(f"{folder}/out/batch={last['number']}") if mode == "complete" else out.option("recursiveFileLookup", True).parquet(f"{folder}/out")


_a5 = [f"a{i}" for i in range(1, 6)]
_small = MD5.with_(s=4, width=200)


def stream_counters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return drained(spark, stream_profile.sketch_stream(event_attrs(events_stream(spark, sf_dir)), _a5, _small, "rid"), "complete")


add("stream_profile_events", lambda sp, sf: shaped(estimate.from_sketch(stream_counters(sp, sf), 5, _small)), counter_sql(_ev, _small) + solved_sql(5, 4, SKETCHED))

_bern = _small.with_(ratio=0.5, sampler="bernoulli")
add("stream_bernoulli_events", lambda sp, sf: shaped(estimate.from_sketch(drained(sp, stream_profile.sketch_stream(event_attrs(events_stream(sp, sf)), _a5, _bern, "rid"), "complete"), 5, _bern)), counter_sql(_ev, _bern) + solved_sql(5, 4, SKETCHED, factor="4"))


_never3 = MD5.with_(s=1, width=300, null_policy="never")


def stream_nulls(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = file_stream(spark, sf_dir, "orders").selectExpr("o_orderkey AS rid", *[f"{e} AS a{i + 1}" for i, e in enumerate(_nulls.attrs)])
    return shaped(estimate.from_sketch(drained(spark, stream_profile.sketch_stream(rows, _nulls.cols, _never3, "rid"), "complete"), 3, _never3))


add("stream_profile_nulls_never", stream_nulls, counter_sql(_nulls, _never3) + solved_sql(3, 1, SKETCHED))
_drip = MD5.with_(s=5, width=200)


def stream_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Near-duplicate pairs of a stream of documents, by super-shingles."""
    rows = W.shingled(file_stream(spark, sf_dir, "documents").selectExpr("doc_id AS rid", "text"))
    return shaped(estimate.from_sketch(drained(spark, stream_profile.sketch_stream(rows, _c6, _drip, "rid"), "complete"), 6, _drip))


add("stream_profile_docs", stream_docs, counter_sql(DOCS6, _drip) + solved_sql(6, 5, SKETCHED))


_win = MD5.with_(s=3, width=100)
_four = ["a1", "a3", "a4", "a5"]


def daily_panes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return drained(spark, stream_profile.tumbling(event_attrs(events_stream(spark, sf_dir)), _four, _win, "rid", "ts", "1 day"), "complete")


def by_day(prof: DataFrame) -> DataFrame:
    return longs(prof, "y", "emitted", "n", "x", "pairs_at_least", "g").select("day", F.col("level").cast("long").alias("level"), "y", "emitted", "n", "x", "pairs_at_least", "g")


def stream_daily(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A profile for each day."""
    return by_day(estimate.from_sketches(daily_panes(spark, sf_dir).withColumn("day", F.to_date("k0.start")), ["day"], 4, _win))


def stream_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A profile for three days from each day on, added up from daily panes."""
    got = stream_profile.sliding_from_panes(daily_panes(spark, sf_dir), 3, 86400)
    return by_day(estimate.from_sketches(got.withColumn("day", F.to_date("start")), ["day"], 4, _win))


def windows_sql(days: int) -> str:
    rows = f"SELECT event_id AS rid, {', '.join(f'{W.EVENTS_DUCK[int(a[1]) - 1]} AS a{i + 1}' for i, a in enumerate(_four))}, CAST(ts AS DATE) AS day FROM events"
    coef = ", ".join(f"({k}, {j}, {c})" for k, j, c in lattice.inversion_matrix(4, 3))
    return f"""{counter_sql(Source(rows, 4), _win, more="day, ")}, kd AS (SELECT CAST(day - CAST(b AS INT) AS DATE) AS day, level, row, bucket, sum(counter) AS counter FROM k, range({days}) r(b) GROUP BY ALL),
nn AS (SELECT CAST(day - CAST(b AS INT) AS DATE) AS day, count(*) AS n FROM t, range({days}) r(b) GROUP BY 1),
mm AS (SELECT day, level, median(f2) AS y FROM (SELECT day, level, row, CAST(sum(counter * counter) AS DOUBLE) AS f2 FROM kd WHERE row >= 0 GROUP BY 1, 2, 3) GROUP BY 1, 2),
lv AS (SELECT day, level, y, emitted, n FROM mm JOIN (SELECT day, level, counter AS emitted FROM kd WHERE row = -1) USING (day, level) JOIN nn USING (day)),
cf(k, level, coef) AS (VALUES {coef}), xs AS (SELECT day, k AS level, sum(coef * (y - emitted)) AS x FROM cf JOIN lv USING (level) GROUP BY 1, 2),
pr AS (SELECT *, sum(x) OVER (PARTITION BY day ORDER BY level DESC) AS p FROM lv JOIN xs USING (day, level))
SELECT day, CAST(level AS BIGINT) AS level, CAST(round(y) AS BIGINT) AS y, CAST(emitted AS BIGINT) AS emitted, n, CAST(round(x) AS BIGINT) AS x, CAST(round(p) AS BIGINT) AS pairs_at_least, CAST(round(p + n) AS BIGINT) AS g FROM pr"""


add("stream_tumbling_daily", stream_daily, windows_sql(1))
add("stream_sliding_3d", stream_sliding, windows_sql(3))


def stream_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = drained(spark, stream_profile.sessions(events_stream(spark, sf_dir), "user_id", "ts", "1 hour"), "complete")
    return got.groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.sum("n_events").alias("events"))


add("stream_sessions", stream_sessions, "SELECT user_id, CAST(sum(new) AS BIGINT) AS sessions, count(*) AS events FROM (SELECT user_id, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 1 HOUR THEN 0 ELSE 1 END AS new FROM events) GROUP BY 1")


def sessions_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The profile over sessions: type of the first event, number of events, day."""
    got = drained(spark, stream_profile.sessions(events_stream(spark, sf_dir), "user_id", "ts", "1 hour"), "complete")
    rows = got.select(F.xxhash64("user_id", "start").alias("rid"), F.col("first_type").alias("a1"), F.col("n_events").alias("a2"), F.col("day").alias("a3"))
    return shaped(estimate.self_join_size(rows, ["a1", "a2", "a3"], EstimatorSpec(s=1), "exact", "rid"))


_sess = """SELECT 0 AS rid, first(event_type ORDER BY ts, event_type) AS a1, count(*) AS a2, CAST(min(ts) AS DATE) AS a3 FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS nr FROM
(SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 1 HOUR THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, nr"""
add("stream_sessions_profile", sessions_profile, profile_sql(_sess, 3))


def stream_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Join size of two streams from their two sketches; no rows are joined."""
    e = event_attrs(events_stream(spark, sf_dir))
    sides = [drained(spark, stream_profile.sketch_stream(e.where(f"a1 % 2 = {k}"), _a5, _small, "rid"), "complete") for k in (0, 1)]
    sizes = [sketch.level_sizes(x).where("level = 0").select(F.col("emitted").alias("n")) for x in sides]
    out = longs(estimate.join_profile(sketch.inner_product(*sides, _small), 5, _small, *sizes), "y", "x", "pairs_at_least")
    return out.select(F.col("level").cast("long").alias("level"), "y", "x", "pairs_at_least", F.round("selectivity", 9).alias("selectivity"))


add("stream_join_events", stream_join, sketch_join_sql(*parts_of(_ev, *_users), _small))


def stream_late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Closed daily windows of a watermarked stream: the last windows stay open behind the watermark."""
    e = stream_profile.event_time(events_stream(spark, sf_dir), "ts", "1 day")
    got = drained(spark, e.groupBy(F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n")), "append")
    return got.select(F.to_date("window.start").alias("day"), "n")


add("stream_late_rows", stream_late, "SELECT CAST(ts AS DATE) AS day, count(*) AS n FROM events GROUP BY 1 HAVING CAST(CAST(ts AS DATE) AS TIMESTAMP) + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 DAY FROM events)")
