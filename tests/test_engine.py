"""Estimates against exact counts, invariants, plans, statistics and streams on small tables."""

import hashlib
import re
from functools import reduce

import pytest
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from conftest import DATA
from pairlattice import measures
from pairlattice import queries as Q
from pairlattice.functions import hashing
from pairlattice.operators import baselines, moments, records, repeats, sketch, strata, subvalues
from pairlattice.plans import estimate
from pairlattice.plans.attributes import choose_attributes
from pairlattice.sources import tables
from pairlattice.sources import workloads as W
from pairlattice.spec import EstimatorSpec

SF = f"{DATA}/sf0.001"
O5 = W.TABLES["orders5"]


def x_of(df: DataFrame) -> dict:
    return {r["level"]: int(r["x"]) for r in df.collect()}


#: Exact pair counts of the smallest size, from the highest level down.
PROFILES = {
    "orders5": [14, 2218, 44174, 320548, 949114],
    "orders6": [0, 108, 3556, 53422, 340804, 948660],
    "lineitem_mixed6": [202, 14340, 291588, 2493620, 9659616, 15487002],
    "lineitem_biblio5": [0, 146, 32218, 1502980, 13411898],
    "part5": [0, 0, 10, 522, 8336],
    "events5": [0, 86, 2906, 45968, 305070],
    "embed8": [970, 7804, 27636, 54456, 67684, 54970, 27310, 7768],
    "customer3": [12, 610, 6204],
    "jointree5": [308, 8756, 90092, 426202, 947330],
    "page_url6": [0, 8, 172, 678, 980, 524],
    "nulls3": [21296, 256962, 942796],
}


@pytest.mark.parametrize("name", sorted(PROFILES))
def test_exact_profiles(spark, name):
    w = W.TABLES[name]
    got = x_of(estimate.self_join_size(w.frame(spark, SF), w.cols, EstimatorSpec(s=1), "exact", "rid"))
    assert [got[k] for k in range(w.d, 0, -1)] == PROFILES[name]


@pytest.mark.parametrize("name", sorted(set(Q.ORACLES)))
def test_queries_equal_their_sql(same, name):
    same(Q.QUERIES[name], Q.ORACLES[name])


@pytest.mark.parametrize("name", ["asymptotic_grid", "bound_grid_exact", "bound_grid_sketch", "half_sum_counterexamples", "hamming_pairs_example", "plan_sketch_size", "subvalues_per_record", "ratio_for_budget", "sample_sizes", "worked_example"])
def test_queries_read_a_given_table(spark, name):
    assert Q.QUERIES[name](spark, SF).inputFiles()


def errors(df: DataFrame, key: str = "method") -> dict:
    """(key, level) -> (runs, mean_error, std_error)."""
    return {(r[key], r["level"]): (r["runs"], r["mean_error"], r["std_error"]) for r in df.collect()}


@pytest.mark.parametrize("name,d", [("exact_vs_strata_orders5", 5), ("exact_vs_strata_orders6", 6)])
def test_exact_mode_spreads_less_than_strata(spark, name, d):
    got = errors(Q.QUERIES[name](spark, SF))
    assert {k[0] for k in got} == {"lattice exact", "lsh strata"} and all(v[0] == 30 for v in got.values())
    for k in range(3, d):
        assert got["lattice exact", k][2] < got["lsh strata", k][2]
        assert abs(got["lattice exact", k][1]) <= 3.5 * got["lattice exact", k][2] / 30**0.5 + 1e-9


def test_spread_falls_with_the_ratio_and_is_not_moved_by_duplication(spark):
    got = errors(Q.QUERIES["ablation_ratio_orders5"](spark, SF), "setting")
    assert got["r=1.0", 3][2] < got["r=0.25", 3][2]
    size = errors(Q.swept([(f"x{x:g}", Q.resized(O5.frame, x), 5, EstimatorSpec(s=3, ratio=0.5)) for x in (0.5, 1, 2)])(spark, SF), "setting")
    assert size["x2", 3][2] < 1.5 * size["x1", 3][2]


def test_spread_grows_with_the_dimension(spark):
    got = errors(Q.swept([(f"d={d}", Q.shingles(d), d, EstimatorSpec(s=d - 2, ratio=0.5)) for d in (4, 8)])(spark, SF), "setting")
    assert got["d=8", 6][2] > got["d=4", 2][2]


def test_materialization_grows_as_the_threshold_falls(spark):
    got = [(r["s"], r["values"], r["lattice_bytes"]) for r in Q.QUERIES["materialization_orders5"](spark, SF).collect()]
    assert [g[0] for g in got] == [5, 4, 3, 2, 1] and got == sorted(got, key=lambda g: g[1:]) and 0.4 * 1500 < got[0][1] < 0.6 * 1500


@pytest.mark.parametrize("name", ["method_costs_orders5", "dedup_advice_docs", "equal_space_doc_shingles6"])
def test_queries_without_sql_run(spark, name):
    assert Q.QUERIES[name](spark, SF).count() > 0


def test_repeats_are_the_single_estimates(spark):
    f = O5.frame(spark, SF)
    spec = EstimatorSpec(s=3, ratio=0.5)
    for mode in ("exact", "sketch"):
        many = estimate.repeated(f, O5.cols, spec, "rid", [2, 5], mode)
        for k in (2, 5):
            one = {r["level"]: float(r["g"]) for r in estimate.self_join_size(f, O5.cols, spec.with_(seed=k), mode, "rid").collect()}
            assert {r["level"]: r["g"] for r in many.where(f"seed = {k}").collect()} == pytest.approx(one)
    strata = lambda **kw: {r["level"]: r["x"] for r in baselines.lsh_strata(f, O5.cols, spec.with_(**kw), "rid").collect()}
    both = baselines.lsh_strata(f, O5.cols, spec, "rid", seeds=[2, 5])
    assert {r["level"]: r["x"] for r in both.where("seed = 5").collect()} == strata(seed=5)


@pytest.mark.parametrize("s,ratio,policy", [(1, 0.5, "equal"), (3, 0.3, "equal"), (2, 0.5, "never"), (2, 1.0, "equal")])
def test_repeated_moments_are_those_of_the_level_streams(spark, s, ratio, policy):
    f = O5.frame(spark, SF).withColumns({"a1": F.expr("if(rid % 3 = 0, null, a1)"), "a2": F.lit("x"), "rid": F.expr("if(rid % 50 = 1, null, rid)")})
    spec = EstimatorSpec(s=s, ratio=ratio, null_policy=policy)
    stream = subvalues.level_stream(f.withColumn("seed", F.explode(F.array(F.lit(2), F.lit(5)))), O5.cols, spec, "rid", True, ["seed"], F.col("seed"))
    rows = lambda df: {(r["seed"], r["level"]): (r["y"], r["emitted"]) for r in df.collect()}
    assert rows(repeats.moments(f, O5.cols, spec, "rid", [2, 5])) == rows(moments.level_moments(stream, ["seed"]))


@pytest.mark.parametrize("kw", [{"seeds": [2, 5, 9]}, {"seeds": [1, 2], "policy": "fraction"}, {"oracle": True, "adaptive": True}])
def test_packed_strata_are_the_joined_ones(spark, monkeypatch, kw):
    f = O5.frame(spark, SF).withColumn("a1", F.expr("if(rid % 3 = 0, null, a1)"))
    run = lambda: sorted(map(tuple, baselines.lsh_strata(f, O5.cols, EstimatorSpec(s=2), "rid", **kw).collect()))
    got = run()
    monkeypatch.setattr(strata, "MOST_BYTES", 0)
    assert got == [pytest.approx(r) for r in run()]


def test_records_of_a_comparison_are_made_once_and_deleted(spark, monkeypatch, tmp_path):
    made = []
    monkeypatch.setattr(Q, "shared_path", lambda spark, what: made.append(what) or f"{tmp_path}/{what}")
    got = errors(Q.QUERIES["exact_vs_strata_doc_shingles6"](spark, SF))
    assert made == ["records"] and not list(tmp_path.iterdir())
    assert set(got) == {(m, k) for m in ("lattice exact", "lsh strata") for k in range(3, 7)} and all(v[0] == 30 for v in got.values())


def test_digests_of_numbers_are_those_of_md5():
    for first, count in ((0, 12), (9_990, 10), (20_000, 7), (123_450_000, 10_000), (2_070_001_234, 8_000)):
        want = [int(hashlib.md5(f"l7|{i}".encode()).hexdigest()[:15], 16) for i in range(first, first + count)]
        assert strata.leading_60(b"l7|", first, count).tolist() == want


def test_join_of_equal_ids_at_unequal_ratios_is_not_biased(spark):
    f = O5.frame(spark, SF)
    true = {r["level"]: float(r["x"]) for r in estimate.join_size(f, f, O5.cols, O5.cols, EstimatorSpec(s=3), "exact", "rid", "rid").collect()}
    got = [{r["level"]: r["x"] for r in estimate.join_size(f, f, O5.cols, O5.cols, EstimatorSpec(s=3, ratio=0.5, seed=k), "exact", "rid", "rid", ratio_b=0.75).collect()} for k in range(10, 50, 10)]
    assert sum(g[3] for g in got) / 4 == pytest.approx(true[3], rel=0.1)


def test_join_fixture_values(spark):
    got = {r["level"]: r["x"] for r in Q.QUERIES["join_profile_orders_even_odd"](spark, SF).collect()}
    assert [got[k] for k in (5, 4, 3, 2, 1)] == [2, 579, 10936, 80418, 237092]


def test_join_with_itself_adds_self_pairs_at_the_top(spark):
    f = O5.frame(spark, SF)
    x = x_of(estimate.self_join_size(f, O5.cols, EstimatorSpec(s=3), "exact", "rid"))
    j = {r["level"]: int(r["x"]) for r in estimate.join_size(f, f, O5.cols, O5.cols, EstimatorSpec(s=3), "exact", "rid", "rid").collect()}
    assert j == {3: x[3], 4: x[4], 5: x[5] + 1500}


def test_counterexamples_break_the_half_sum_bound(spark):
    for a, b, s, size in W.counterexamples(spark):
        r = baselines.half_sum_bound(a, b, ["a1", "a2", "a3"], s).first()
        assert r["join_size"] == size > r["bound"]


def test_pair_sampling_example(spark):
    e = W.example_relation(spark).where("rid in (1, 3)")
    got = estimate.self_join_size(e, ["a1", "a2", "a3"], EstimatorSpec(s=1), "exact", "rid")
    assert {k: v * 4 * 3 / (2 * 1) for k, v in x_of(got).items()} == {3: 0, 2: 12, 1: 0}


def test_empty_single_and_identical(spark):
    one = "rid long, a1 string, a2 string"
    for rows, g in (([], 0), ([(1, "x", "y")], 1), ([(i, "x", "y") for i in range(7)], 49)):
        df = spark.createDataFrame(rows, one)
        got = {r["level"]: (int(r["g"]), r["selectivity"]) for r in estimate.self_join_size(df, ["a1", "a2"], EstimatorSpec(s=1), "exact", "rid").collect()}
        assert {k: v[0] for k, v in got.items()} == {1: g, 2: g}
        assert (got[1][1] is None) == (not rows)
        sk = {r["level"]: r["g"] for r in estimate.self_join_size(df, ["a1", "a2"], EstimatorSpec(s=1), "sketch", "rid").collect()}
        assert sk == {1: g, 2: g}


def test_null_and_delimiter_traps(spark):
    nulls = spark.createDataFrame([(1, None, 1), (2, 1, None)], "rid long, a1 int, a2 int")
    text = spark.createDataFrame([(1, "a.b", "c"), (2, "a", "b.c")], "rid long, a1 string, a2 string")
    for fp in ("xx64", "md5_60", "raw"):
        for df in (nulls, text):
            assert x_of(estimate.self_join_size(df, ["a1", "a2"], EstimatorSpec(s=1, fingerprint=fp), "exact", "rid")) == {1: 0, 2: 0}


def test_draws_depend_on_identity_not_values(spark):
    df = spark.createDataFrame([(i, "x", "y", "z") for i in range(400)], "rid long, a1 string, a2 string, a3 string")
    spec = EstimatorSpec(s=3, ratio=0.5)
    kept = subvalues.level_stream(df, ["a1", "a2", "a3"], spec, "rid").count()
    assert 140 < kept < 260
    assert records.numbered(df.select("a1", "a2", "a3")).select("rid").distinct().count() == 400


def test_fixed_draws_are_without_replacement_and_sized(spark):
    f = O5.frame(spark, SF)
    s = subvalues.level_stream(f, O5.cols, EstimatorSpec(s=3, ratio=0.5), "rid")
    per = s.groupBy("rid", "level").agg(F.count("mask").alias("n"), F.count_distinct("mask").alias("k"))
    assert per.where("n <> k").count() == 0
    assert per.where("level = 3 and n <> 5").count() == 0
    assert per.where("level = 4 and n not in (2, 3)").count() == 0


def test_invariants(spark):
    f = O5.frame(spark, SF)
    spec = EstimatorSpec(s=1)
    got = {r["level"]: r for r in estimate.self_join_size(f, O5.cols, spec, "exact", "rid").collect()}
    g = [int(got[k]["g"]) for k in range(5, 0, -1)]
    assert g == sorted(g) and g[-1] <= 1500 * 1500
    assert all(int(r["x"]) % 2 == 0 for r in got.values())
    moved = x_of(estimate.self_join_size(f.repartition(13), O5.cols[::-1], spec, "exact", "rid"))
    assert moved == {k: int(r["x"]) for k, r in got.items()}


@pytest.mark.parametrize("times", [2, 3])
def test_duplication_law(spark, times):
    f = O5.frame(spark, SF)
    g = lambda df: {r["level"]: int(r["g"]) for r in estimate.self_join_size(df, O5.cols, EstimatorSpec(s=3), "exact", "rid").collect()}
    assert g(W.duplicated(f, times)) == {k: v * times * times for k, v in g(f).items()}


@pytest.mark.parametrize("name,want", [("pairs_40_60", 3600), ("pairs_20_80", 72000)])
def test_generated_sets(spark, name, want):
    got = x_of(estimate.self_join_size(W.generated_pairs(spark, SF, *W.GENERATED[name]), O5.cols, EstimatorSpec(s=1), "exact", "rid"))
    assert got == {5: 0, 4: want, 3: 0, 2: 0, 1: 0}


def test_tab4_column_equals_python(spark):
    import random

    rng = random.Random(2)
    values = [0, (1 << 60) - 1, *[rng.randrange(1 << 60) for _ in range(500)]]
    c = hashing.coefficients(5, 1, "bucket")
    got = spark.createDataFrame([(v,) for v in values], "v long").select("v", hashing.tab4(c, F.col("v")).alias("h")).collect()
    assert all(r["h"] == hashing.tab4_value(c, r["v"]) for r in got)


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_sketch_is_linear_and_engines_agree(spark, tmp_path):
    f = O5.frame(spark, SF)
    spec = EstimatorSpec(s=4, width=100)
    make = lambda df: sketch.build(subvalues.level_stream(df, O5.cols, spec, "rid", True), spec)
    whole, a, b = make(f), make(f.where("a5 < 6")), make(f.where("a5 >= 6"))
    assert rows(sketch.merge(a, b)) == rows(whole)
    back = sketch.subtract(whole, b).where("counter <> 0")
    assert rows(back) == rows(a.where("counter <> 0"))
    assert rows(sketch.build_arrow(subvalues.level_stream(f, O5.cols, spec, "rid", True), spec)) == rows(whole)
    sketch.save(whole, str(tmp_path / "s"))
    assert rows(sketch.load(spark, str(tmp_path / "s"))) == rows(whole)


def test_join_sketch_of_a_relation_with_itself_is_its_moment(spark):
    f = O5.frame(spark, SF)
    spec = EstimatorSpec(s=4)
    k = sketch.build(subvalues.level_stream(f, O5.cols, spec, "rid"), spec)
    assert {r[0]: r[1] for r in sketch.inner_product(k, k, spec).collect()} == {r[0]: r[1] for r in sketch.second_moment(k, spec).select("level", "y").collect()}


def test_sampling_engines_agree_and_scale_is_null_for_one_record(spark):
    f = O5.frame(spark, SF)
    a = rows(baselines.pair_sampling(f, O5.cols, EstimatorSpec(s=3), "rid", size=300))
    assert a == rows(baselines.pair_sampling(f, O5.cols, EstimatorSpec(s=3), "rid", size=300, engine="lattice"))
    assert baselines.pair_sampling(f, O5.cols, EstimatorSpec(s=3), "rid", size=1).first()["x"] is None


def test_miners_agree(spark):
    f = O5.frame(spark, SF)
    found = lambda m, support=5: {(r["mask"], r["fp"]): r["c"] for r in baselines.patterns(f, O5.cols, 3, support, m, record_id="rid").collect()}
    true = found("partition")
    assert found("levelwise") == true
    assert found("sample").items() <= true.items()
    every = {(r["mask"], r["fp"]): r["c"] for r in moments.counts(subvalues.level_stream(f, O5.cols, EstimatorSpec(s=3), "rid")).collect()}
    short = found("lossy", 20)
    assert {k for k, c in every.items() if c >= 20} <= set(short)
    assert all(every[k] - 10 <= c <= every[k] for k, c in short.items())


def test_miners_count_repeated_rows(spark):
    df = spark.createDataFrame([(1, 1, 1)] * 4 + [(1, 1, 2)], "a1 int, a2 int, a3 int")
    want = {1: [5], 2: [5], 3: [5], 4: [4], 5: [4], 6: [4], 7: [4]}
    for m in ("levelwise", "partition"):
        got: dict = {}
        for r in baselines.patterns(df, ["a1", "a2", "a3"], 1, 2, m).collect():
            got.setdefault(r["mask"], []).append(r["c"])
        assert got == want


def test_streams_treat_nulls_and_zeros_as_tables_do(spark):
    from pairlattice.streaming import profile as P

    rows = spark.createDataFrame([(i, None if i % 2 else 0.0 if i % 4 else -0.0, "x") for i in range(6)], "rid long, a1 double, a2 string")
    for policy in ("equal", "never", "drop"):
        spec = EstimatorSpec(s=1, null_policy=policy, width=500)
        want = x_of(estimate.self_join_size(rows, ["a1", "a2"], spec, "exact", "rid"))
        assert x_of(estimate.from_sketch(P.sketch_stream(rows, ["a1", "a2"], spec, "rid"), 2, spec)) == want


def test_lsh_strata_lookup_is_exact_when_pairs_are_many(spark):
    f = O5.frame(spark, SF)
    true = x_of(estimate.self_join_size(f, O5.cols, EstimatorSpec(s=3), "exact", "rid"))
    got = {r["level"]: r["x"] for r in baselines.lsh_strata(f, O5.cols, EstimatorSpec(s=3), "rid", sizes=(20000, 20000)).collect()}
    assert got[3] == pytest.approx(true[3], rel=0.25)


def spread(spark, frame, cols, spec, mode, seeds=range(1, 13)):
    true = estimate.self_join_size(frame, cols, spec.with_(ratio=1.0), "exact", "rid")
    runs = estimate.repeated(frame, cols, spec, "rid", seeds, mode).select("seed", "level", "g")
    return {r["level"]: r for r in measures.summary(measures.relative_error(runs, true)).collect()}


def test_drawn_estimates_center_on_the_truth(spark):
    f = W.generated_pairs(spark, SF, 0.2, 16).limit(2000)
    got = spread(spark, f, O5.cols, EstimatorSpec(s=4, ratio=0.5), "exact")
    for r in got.values():
        assert abs(r["mean_error"]) <= 3.5 * r["std_error"] / 12**0.5 + 1e-9


def test_sketch_error_falls_with_width(spark):
    f = O5.frame(spark, SF)
    narrow = spread(spark, f, O5.cols, EstimatorSpec(s=3, width=20, combine="mean"), "sketch")
    wide = spread(spark, f, O5.cols, EstimatorSpec(s=3, width=2000, combine="mean"), "sketch")
    assert wide[3]["std_error"] < narrow[3]["std_error"]


def test_plan_is_one_scan_without_python(spark):
    df = estimate.self_join_size(O5.frame(spark, SF), O5.cols, EstimatorSpec(s=3), "sketch", "rid")
    plan = df._jdf.queryExecution().executedPlan().toString()
    stream = sketch.build(subvalues.level_stream(O5.frame(spark, SF), O5.cols, EstimatorSpec(s=3), "rid"), EstimatorSpec(s=3))
    one = stream._jdf.queryExecution().executedPlan().toString()
    assert len(re.findall(r"FileScan", one)) == 1 and one.count("Exchange hashpartitioning") == 1
    assert "partial_sum" in one and "Python" not in plan and "CartesianProduct" not in plan
    assert "o_comment" not in one and "o_totalprice" not in one


def test_streams_equal_batches(spark, tmp_path):
    from pairlattice.streaming import profile as P

    raw = Q.event_attrs(spark.read.parquet(f"{SF}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp")))
    spec = EstimatorSpec(s=4, width=50)
    batch = P.sketch_stream(raw, Q._a5, spec, "rid")
    halves = tmp_path / "in"
    raw.where("a1 % 2 = 0").coalesce(1).write.parquet(str(halves))
    src = lambda: tables.stream(spark, str(halves), raw.schema, files_per_trigger=1)
    seen = []
    q = P.start_profile(src(), Q._a5, spec, "rid", lambda prof, i: seen.append((i, prof.collect())), str(tmp_path / "c"))
    q.awaitTermination()
    raw.where("a1 % 2 = 1").coalesce(1).write.mode("append").parquet(str(halves))
    q = P.start_profile(src(), Q._a5, spec, "rid", lambda prof, i: seen.append((i, prof.collect())), str(tmp_path / "c"))  # a restart goes on from its state
    q.awaitTermination()
    assert sorted(map(tuple, seen[-1][1])) == rows(estimate.from_sketch(batch, 5, spec))
    whole = P.sketch_stream(raw.withColumn("w", F.lit(1)).unionByName(raw.where("a1 = 3").withColumn("w", F.lit(-1))), Q._a5, spec, "rid", weight="w")
    assert rows(whole.where("counter <> 0")) == rows(P.sketch_stream(raw.where("a1 <> 3"), Q._a5, spec, "rid").where("counter <> 0"))


@pytest.mark.parametrize("name,key", [("documents", "doc_id"), ("events", "event_id")])
def test_streams_read_tables_of_several_files(spark, tmp_path, name, key):
    table = spark.read.parquet(f"{SF}/{name}.parquet")
    table.repartition(3).write.parquet(str(tmp_path / f"{name}.parquet"))
    for folder in (SF, str(tmp_path)):
        got = Q.drained(spark, Q.file_stream(spark, folder, name).select(key), "append")
        assert rows(got) == rows(table.select(key))


@pytest.mark.parametrize("policy", ["equal", "never", "drop"])
def test_all_pairs_of_many_records(spark, policy):
    raw = [(i, None if i % 5 == 0 else i % 3, "xyz"[i % 2], None if i % 7 == 0 else i // 20) for i in range(60)]
    kept = [r for r in raw if policy != "drop" or None not in r]
    agree = lambda a, b: sum(x == y and (policy != "never" or x is not None) for x, y in zip(a[1:], b[1:]))
    want: dict = {}
    for a in kept:
        for b in kept:
            if a[0] != b[0]:
                want[agree(a, b)] = want.get(agree(a, b), 0) + 1
    df = spark.createDataFrame(raw, "rid long, a1 int, a2 string, a3 int")
    for most in (20_000, 5):  # one by one, and by subsets
        assert {r["level"]: r["x"] for r in baselines.all_pairs(df, ["a1", "a2", "a3"], "rid", most, policy).collect()} == want


def broadcast_scans(df: DataFrame) -> int:
    """Scans of files below a broadcast, in the plan before it adapts."""
    found, inside = 0, None
    for line in df._jdf.queryExecution().executedPlan().toString().splitlines():
        at = len(line) - len(line.lstrip(" :+-"))
        if inside is not None and at <= inside:
            inside = None
        if inside is None and "BroadcastExchange" in line:
            inside = at
        found += inside is not None and "FileScan" in line
    return found


def test_levelwise_broadcasts_no_records(spark):
    found = baselines.patterns(O5.frame(spark, SF), O5.cols, 3, 4, "levelwise", record_id="rid")
    assert broadcast_scans(found) == 0


@pytest.mark.parametrize("kind,policy", [("long", "equal"), ("int", "never"), ("long", "drop")])
def test_counters_of_repeats_are_those_of_single_sketches(spark, kind, policy):
    raw = [(None if i == 5 else i * 7 - 90, None if i % 5 == 0 else i % 3, "xyz"[i % 2], None if i % 7 == 0 else i // 4) for i in range(300)]
    df, cols = spark.createDataFrame(raw, f"rid {kind}, a1 int, a2 string, a3 int"), ["a1", "a2", "a3"]
    for ratio in (0.4, 1.0):
        spec = EstimatorSpec(s=1, ratio=ratio, null_policy=policy, width=40)
        many = repeats.counters(df, cols, spec, "rid", [3, 8]).where("counter <> 0")
        for k in (3, 8):
            one = spec.with_(seed=k)
            want = sketch.build(subvalues.level_stream(df, cols, one, "rid", True), one).where("counter <> 0")
            assert rows(many.where(f"seed = {k}").drop("seed")) == rows(want)


def test_choices_and_functions(spark, tmp_path):
    f = O5.frame(spark, SF)
    assert choose_attributes(f, O5.cols, 2) == ["a1", "a5"]
    assert choose_attributes(f, O5.cols, 2, "first") == ["a1", "a2"]
    from pairlattice.functions.sql import register

    register(spark)
    assert spark.sql("select binomial(5, 2) b").first()["b"] == 10
    assert rows(spark.sql("select * from similarity_profile_of(array(16L, 4L), 4, 3, 2)")) == [(2, 4.0), (3, 0.0)]
    a = spark.createDataFrame([(5, 6)], "x long, y long").select(records.hamming_bits(F.col("x"), F.col("y")).alias("d")).first()["d"]
    assert a == 2 and records.threshold_from_similarity(5, 0.8) == 4
    tables.write(f.limit(5), str(tmp_path / "t"), "orc")
    assert tables.read(spark, str(tmp_path / "t"), "orc").count() == 5
    with pytest.raises(ValueError):
        tables.read(spark, "x", "csv")
    assert reduce(lambda p, q: p + q, [moments.column_cardinalities(f, ["a2"]).first()["n_distinct"]]) == 3


def test_entry(spark):
    import __spark_entry__ as e

    out = e.entry(spark)
    assert out.count() == 3 and set(e.oracle_sql()) <= set(e.queries())


def test_error_falls_with_the_ratio_and_not_with_duplication(spark):
    f = W.generated_pairs(spark, SF, 0.2, 16).limit(1500)
    low, high = (spread(spark, f, O5.cols, EstimatorSpec(s=4, ratio=r), "exact", range(1, 9))[4]["std_error"] for r in (0.25, 0.75))
    assert high < low
    twice = spread(spark, W.duplicated(f, 2), O5.cols, EstimatorSpec(s=4, ratio=0.25), "exact", range(1, 9))[4]["std_error"]
    assert twice < 1.5 * low


def test_replacement_draws_are_biased(spark):
    f = W.generated_pairs(spark, SF, 0.2, 16).limit(1500)
    fair, odd = (spread(spark, f, O5.cols, EstimatorSpec(s=4, ratio=0.8, sampler=m), "exact", range(1, 7))[4]["mean_error"] for m in ("fixed", "replacement"))
    assert abs(odd) > abs(fair)


def test_sample_of_a_stream_is_the_sample_of_the_table(spark, tmp_path):
    from pairlattice.streaming import profile as P

    f = O5.frame(spark, SF)
    f.repartition(3).write.parquet(str(tmp_path / "in"))
    stored = str(tmp_path / "store")
    src = lambda: tables.stream(spark, str(tmp_path / "in"), f.schema, files_per_trigger=1)
    P.sample_stream(src(), 50, 7, "rid", stored, str(tmp_path / "c")).awaitTermination()
    last = max(int(p.name) for p in (tmp_path / "store").iterdir())
    sample, n = P.stored_sample(spark, stored, last)
    want = f.withColumn("h", F.xxhash64(F.lit(7), "rid")).orderBy("h").limit(50)
    assert n == 1500 and sorted(r["rid"] for r in sample.collect()) == sorted(r["rid"] for r in want.collect())
    more = f.limit(3).selectExpr("-rid - 1 AS rid", "a1", "a2", "a3", "a4", "a5")
    more.coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    P.sample_stream(src(), 50, 7, "rid", stored, str(tmp_path / "c")).awaitTermination()  # a restart goes on from the stored sample
    assert P.stored_sample(spark, stored, last + 1)[1] == 1503


def test_matching_sample_grows_until_it_is_good_enough(spark):
    f = O5.frame(spark, SF)
    size, e = measures.matching_sample(f, O5.cols, EstimatorSpec(s=3), "rid", 0.2, [1, 2, 3], [20, 700, 1500])
    assert size in (700, 1500) and 0 < e <= 1
