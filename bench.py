"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

``queries`` holds the seconds of each, run once (cold), ``warm`` those of a second run.  ``n_slope`` is
the growth of the sketch's time and of sampling's, whose sample is n^0.998 records compared pair by
pair, over three sizes (1: in proportion to n, 2: quadratic); ``std_g`` the spread of the relative
error of both at equal space, over ten runs.
"""

from __future__ import annotations

import json
import math
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def main() -> None:
    from pyspark.sql import SparkSession
    from pyspark.sql import functions as F

    from pairlattice import measures
    from pairlattice import queries as Q
    from pairlattice.operators.baselines import pair_sampling
    from pairlattice.plans import estimate
    from pairlattice.sources import workloads as W
    from pairlattice.spec import EstimatorSpec

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "12g").config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")

    def timed(df) -> float:
        start = time.perf_counter()
        df.write.format("noop").mode("overwrite").save()
        return time.perf_counter() - start

    o5 = W.TABLES["orders5"]
    sketch = lambda f, seed=7, ratio=1.0: estimate.self_join_size(f, o5.cols, EstimatorSpec(s=3, seed=seed, ratio=ratio), "sketch", "rid")
    names = [
        "profile_orders5", "profile_events5", "profile_doc_shingles6", "sampled_fixed_orders5_r50",
        "sketch_profile_orders5", "sketch_profile_events5", "sketch_profile_doc_shingles6", "join_profile_orders_even_odd", "sketch_join_orders",
        "pair_sampling_orders5", "signature_patterns_orders5_lattice", "lsh_strata_linear_orders5", "stream_profile_events",
    ]
    shingled = lambda *_: estimate.self_join_size(W.shingle_frame(spark, SF, oracle=False), [f"a{i}" for i in range(1, 7)], EstimatorSpec(s=3, ratio=0.5), "sketch", "rid")
    seconds, warm = {}, {}
    for name in names:
        run = shingled if name == "sketch_profile_doc_shingles6" else Q.QUERIES[name]
        seconds[name] = round(timed(run(spark, SF)), 3)
        warm[name] = round(timed(run(spark, SF)), 3)
        print(name, seconds[name], warm[name], file=sys.stderr, flush=True)
    # time against n: an eighth, a quarter and half of the table
    frame = o5.frame(spark, SF)
    n = frame.count()
    times = {"sketch": [], "sampling": []}
    parts = (8, 4, 2)
    for k in parts:
        f = frame.where(F.pmod(F.xxhash64("rid"), F.lit(k)) == 0)
        times["sketch"].append(timed(sketch(f)))
        times["sampling"].append(timed(pair_sampling(f, o5.cols, EstimatorSpec(s=3), "rid", size=lambda m: round(m**0.998), most=n)))
    print(times, file=sys.stderr, flush=True)
    slope = {k: round(math.log(v[-1] / v[0], parts[0] / parts[-1]), 2) for k, v in times.items()}
    # spread of the error at equal space, on the skewed generated set
    g = W.generated_pairs(spark, SF, *W.GENERATED["pairs_20_80"])
    true = estimate.self_join_size(g, o5.cols, EstimatorSpec(s=4), "exact", "rid")
    std, spec, seeds = {}, EstimatorSpec(s=4), range(1, 11)
    for name, runs in (("sketch", estimate.repeated(g, o5.cols, spec, "rid", seeds, "sketch")), ("sampling", pair_sampling(g, o5.cols, spec, "rid", size=1000, engine="lattice", seeds=seeds))):
        runs = runs.select("seed", "level", F.col("g").cast("double").alias("g"))
        std[name] = round(measures.summary(measures.relative_error(runs, true)).where("level = 4").first()["std_error"], 4)
    spark.stop()
    print(json.dumps({"metric": "total seconds of headline queries", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "warm": warm, "sf": SF, "n_slope": slope, "std_g": std, "seconds_by_n": {k: [round(x, 2) for x in v] for k, v in times.items()}, "rows_per_second_sketch": round(n / warm["sketch_profile_orders5"])}))


if __name__ == "__main__":
    main()
