"""Accuracy and cost measures over repeated estimates."""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pairlattice.operators import subvalues
from pairlattice.plans import bounds, estimate
from pairlattice.spec import EstimatorSpec


def relative_error(est: DataFrame, true: DataFrame) -> DataFrame:
    """(.., level, error, abs_error) of ``g`` against the exact profile."""
    t = true.select("level", F.col("g").cast("double").alias("true_g"))
    e = (F.col("g").cast("double") - F.col("true_g")) / F.nullif(F.col("true_g"), F.lit(0.0))
    return est.join(F.broadcast(t), "level").withColumn("error", e).withColumn("abs_error", F.abs("error"))


def summary(errors: DataFrame, *keys: str) -> DataFrame:
    """(keys.., level, runs, mean_error, std_error, mean_abs_error) over repeats."""
    return errors.groupBy(*keys, "level").agg(F.count("error").alias("runs"), F.avg("error").alias("mean_error"), F.stddev_samp("error").alias("std_error"), F.avg("abs_error").alias("mean_abs_error"))


def deleted(spark: SparkSession, path: str) -> None:
    jvm = spark._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def materialization(df: DataFrame, attrs: Sequence[str], spec: EstimatorSpec, record_id: str, folder: str) -> DataFrame:
    """(s, values, lattice_bytes, lsh_bytes): what several passes have to keep on disk, by threshold.

    The lattice keeps the drawn sub-values of the levels from s up, an LSH-based sampler its records by bucket.
    """
    from pairlattice.operators.baselines import lsh_buckets

    d, spark = len(attrs), df.sparkSession
    buckets = materialized_bytes(lsh_buckets(df, attrs, record_id, seed=spec.seed), f"{folder}/lsh")
    rows, values, size = [], 0, 0
    for k in range(d, spec.s - 1, -1):
        path = f"{folder}/level-{k}"
        size += materialized_bytes(subvalues.level_stream(df, attrs, spec, record_id).where(F.col("level") == k).select("mask", "fp"), path)
        values += spark.read.parquet(path).count()
        rows.append((k, values, size, buckets))
    deleted(spark, folder)
    return spark.createDataFrame(rows, "s int, values long, lattice_bytes long, lsh_bytes long")


def timed(action: Callable[[], object]) -> tuple[object, float]:
    start = time.perf_counter()
    out = action()
    return out, time.perf_counter() - start


def materialized_bytes(df: DataFrame, path: str) -> int:
    """Bytes of the files that a table takes when written; sums over the file system that holds them."""
    df.write.mode("overwrite").parquet(path)
    jvm = df.sparkSession._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).getContentSummary(p).getLength()


def record_bytes(df: DataFrame, attrs: Sequence[str]) -> float:
    """Mean length of a record's attributes as text."""
    size = sum((F.coalesce(F.octet_length(F.col(a).cast("string")), F.lit(0)) for a in attrs), F.lit(0))
    return float(df.agg(F.avg(size)).first()[0] or 0)


def space_table(df: DataFrame, attrs: Sequence[str], s: int, width: int = 1000, depth: int = 3) -> DataFrame:
    """Bytes of the sketches (4-byte counters as counted in print, 8-byte as stored) and the sample of equal size."""
    d, size = len(attrs), record_bytes(df, attrs)
    rows = [(d, k, bounds.sketch_bytes(d, k, width, depth), bounds.sketch_bytes(d, k, width, depth, 8), bounds.sample_size_for_bytes(bounds.sketch_bytes(d, k, width, depth), max(size, 1))) for k in range(s, d + 1)]
    return df.sparkSession.createDataFrame(rows, "d int, s int, bytes4 long, bytes8 long, equal_sample long")


def matching_sample(df: DataFrame, attrs: Sequence[str], spec: EstimatorSpec, record_id: str, target_std: float, seeds: Sequence[int], sizes: Sequence[int]) -> tuple[int, float]:
    """Least of ``sizes`` at which sampling's error spread is at most ``target_std``, and its exponent of n."""
    from pairlattice.operators.baselines import pair_sampling

    true = estimate.self_join_size(df, attrs, spec.with_(ratio=1.0), "exact", record_id)
    n = df.count()
    for size in sizes:
        runs = pair_sampling(df, attrs, spec, record_id, size=size, engine="lattice", seeds=seeds)
        got = summary(relative_error(runs, true)).where(F.col("level") == spec.s).first()
        if got["std_error"] is not None and got["std_error"] <= target_std:
            return size, bounds.matching_exponent(n, size)
    return n, 1.0
