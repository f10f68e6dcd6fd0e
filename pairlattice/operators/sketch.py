"""Signed-counter sketches of level streams: linear, mergeable, built by one partial aggregation.

A sketch is a table (level, row, bucket, counter).  Row -1 counts the sub-values of a level; of level
0 that is the number of records.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pairlattice.functions.hashing import coefficients, tab4
from pairlattice.spec import EstimatorSpec

LOW60 = (1 << 60) - 1


def coefficient_rows(spec: EstimatorSpec, seed: int) -> list[tuple[int, int, list[int], list[int]]]:
    """(row, counter, sign, bucket): the polynomials of each row of counters, those of row -1 unused."""
    none = [0] * 12
    flat = lambda c: [v for p in c for v in p]
    if spec.kind == "fast":
        rows = [(r, 0, flat(coefficients(seed, r, "sign")), flat(coefficients(seed, r, "bucket"))) for r in range(spec.depth)]
    else:  # every counter is touched; a counter has signs of its own
        rows = [(j // spec.width, j % spec.width, flat(coefficients(seed, j, "plain")), none) for j in range(spec.width * spec.depth)]
    return [(-1, 0, none, none), *rows]


def updates(stream: DataFrame, spec: EstimatorSpec, keep: Sequence[str] = (), seeds: Sequence[int] | None = None) -> DataFrame:
    """(keep.., level, row, bucket, sign): what each sub-value adds to the counters.

    ``seeds``: the stream has a column ``seed``, also in ``keep``, and there is a sketch for each.
    """
    fp = F.col("fp").bitwiseAND(F.lit(LOW60))
    if seeds is None:  # the coefficients travel as rows of a literal, so the hash is compiled once, not once for each row of counters
        longs = lambda c: F.array(*[F.lit(v).cast("long") for v in c])
        table = F.array(*[F.struct(F.lit(r).alias("row"), F.lit(j).alias("j"), longs(s).alias("s"), longs(b).alias("b")) for r, j, s, b in coefficient_rows(spec, spec.seed)])
        out = stream.select(*keep, "level", fp.alias("fp"), F.explode(table).alias("t"))
    else:
        rows = [(k, *r) for k in seeds for r in coefficient_rows(spec, k)]
        table = stream.sparkSession.createDataFrame(rows, "seed int, row int, j int, s array<bigint>, b array<bigint>")  # seeds x rows of counters
        out = stream.join(F.broadcast(table), "seed").select(*keep, "level", fp.alias("fp"), F.struct("row", "j", "s", "b").alias("t"))
    out = out.where("t.row = -1 or level > 0")
    poly = lambda name: [[F.get(F.col(f"t.{name}"), F.lit(4 * k + i)) for i in range(4)] for k in range(3)]
    counts = F.col("t.row") == -1
    sign = F.when(counts | (tab4(poly("s"), F.col("fp")).bitwiseAND(F.lit(1)) == 1), 1).otherwise(-1)
    bucket = (tab4(poly("b"), F.col("fp")) % F.lit(spec.width)).cast("int") if spec.kind == "fast" else F.col("t.j")
    return out.select(*keep, "level", F.col("t.row").alias("row"), F.when(counts, F.lit(0)).otherwise(bucket).alias("bucket"), sign.alias("sign"))


def build(stream: DataFrame, spec: EstimatorSpec) -> DataFrame:
    """The sketch of a level stream; each task sends at most one row per counter."""
    if spec.fingerprint == "raw":
        raise ValueError("a sketch needs fingerprints; use xx64 or md5_60")
    return updates(stream, spec).groupBy("level", "row", "bucket").agg(F.sum("sign").alias("counter"))


def build_arrow(stream: DataFrame, spec: EstimatorSpec) -> DataFrame:
    """The same counters from numpy arrays, one set per task; for many rows of counters."""
    coef = {(row, what): coefficients(spec.seed, row, what) for row in range(spec.depth) for what in ("sign", "bucket")}
    if spec.kind != "fast":
        raise ValueError("only the fast kind has this engine")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        count: dict[int, int] = {}
        p = np.uint64(2147483647)

        def poly(c: list[int], x: np.ndarray) -> np.ndarray:
            out = np.full(len(x), c[0], np.uint64)
            for a in c[1:]:
                out = (out * x + np.uint64(a)) % p
            return out

        def hash_of(c: list[list[int]], fp: np.ndarray) -> np.ndarray:
            low, high = fp & np.uint64((1 << 30) - 1), fp >> np.uint64(30)
            return (poly(c[0], low) + poly(c[1], high) + poly(c[2], (low + high) % p)) % p

        for b in batches:
            level = b.column(0).to_numpy()
            fp = b.column(1).to_numpy().astype(np.uint64) & np.uint64(LOW60)
            for k in np.unique(level).tolist():
                f = fp[level == k]
                count[k] = count.get(k, 0) + len(f)
                if k == 0:
                    continue
                t, hit = total.setdefault(k, (np.zeros((spec.depth, spec.width), np.int64), np.zeros((spec.depth, spec.width), bool)))
                for row in range(spec.depth):
                    sign = np.where(hash_of(coef[row, "sign"], f) & np.uint64(1), 1, -1)
                    bucket = (hash_of(coef[row, "bucket"], f) % np.uint64(spec.width)).astype(np.int64)
                    t[row] += np.bincount(bucket, sign, spec.width).astype(np.int64)
                    hit[row, bucket] = True
        rows = [(k, -1, 0, n) for k, n in count.items()]
        for k, (t, hit) in total.items():
            r, c = np.nonzero(hit)
            rows.extend(zip([k] * len(r), r.tolist(), c.tolist(), t[r, c].tolist()))
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(x, kind) for x, kind in zip(zip(*rows), (pa.int32(), pa.int32(), pa.int32(), pa.int64()))], names=["level", "row", "bucket", "counter"])

    part = stream.select("level", "fp").mapInArrow(run, "level int, row int, bucket int, counter long")
    return part.groupBy("level", "row", "bucket").agg(F.sum("counter").alias("counter"))


def merge(*sketches: DataFrame) -> DataFrame:
    """The sketch of all streams together."""
    out = sketches[0]
    for s in sketches[1:]:
        out = out.unionByName(s)
    return out.groupBy("level", "row", "bucket").agg(F.sum("counter").alias("counter"))


def subtract(a: DataFrame, b: DataFrame) -> DataFrame:
    """The sketch of ``a`` without what ``b`` counted."""
    return merge(a, b.withColumn("counter", -F.col("counter")))


def save(sketch: DataFrame, path: str, mode: str = "overwrite") -> None:
    sketch.write.mode(mode).partitionBy("level").parquet(path)


def load(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("row int, bucket int, counter long, level int").parquet(path).select("level", "row", "bucket", "counter")


def combined(values: str, how: str) -> Column:
    return F.median(values) if how == "median" else F.avg(values)


def row_moments(sketch: DataFrame, spec: EstimatorSpec, keys: Sequence[str] = ()) -> DataFrame:
    """(keys.., level, row, f2): the estimate of each row of counters."""
    sq = F.col("counter").cast("decimal(19,0)") * F.col("counter").cast("decimal(19,0)")
    out = sketch.where("row >= 0").groupBy(*keys, "level", "row").agg(F.sum(sq).cast("double").alias("f2"))
    return out.withColumn("f2", F.col("f2") / spec.width) if spec.kind == "plain" else out


def level_sizes(sketch: DataFrame, keys: Sequence[str] = ()) -> DataFrame:
    """(keys.., level, emitted) of each level, n at level 0."""
    return sketch.where("row = -1").select(*keys, "level", F.col("counter").alias("emitted"))


def second_moment(sketch: DataFrame, spec: EstimatorSpec, keys: Sequence[str] = ()) -> DataFrame:
    """(keys.., level, y, emitted): moments by the median (or mean) of the rows."""
    y = row_moments(sketch, spec, keys).groupBy(*keys, "level").agg(combined("f2", spec.combine).alias("y"))
    return level_sizes(sketch, keys).where("level > 0").join(y if keys else F.broadcast(y), [*keys, "level"], "left").select(*keys, "level", F.coalesce("y", F.lit(0.0)).alias("y"), "emitted")


def inner_product(a: DataFrame, b: DataFrame, spec: EstimatorSpec) -> DataFrame:
    """(level, y): join sizes of the streams of two sketches with the same seeds."""
    both = a.where("row >= 0").withColumnRenamed("counter", "ca").join(b.where("row >= 0").withColumnRenamed("counter", "cb"), ["level", "row", "bucket"])
    rows = both.groupBy("level", "row").agg(F.sum(F.col("ca").cast("decimal(19,0)") * F.col("cb").cast("decimal(19,0)")).cast("double").alias("f2"))
    levels = a.where("row >= 0").select("level", "row").distinct()
    rows = levels.join(rows, ["level", "row"], "left").fillna(0.0, ["f2"])
    if spec.kind == "plain":
        rows = rows.withColumn("f2", F.col("f2") / spec.width)
    return rows.groupBy("level").agg(combined("f2", spec.combine).alias("y"))
