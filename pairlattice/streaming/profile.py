"""Profiles of streams: the sketch is the state, its size does not depend on the stream's length."""

from __future__ import annotations

from collections.abc import Callable, Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pairlattice.operators import sketch, subvalues
from pairlattice.plans import estimate
from pairlattice.spec import EstimatorSpec


def sketch_stream(df: DataFrame, attrs: Sequence[str], spec: EstimatorSpec, record_id: str, by: Sequence[Column] = (), weight: str | None = None) -> DataFrame:
    """(keys.., level, row, bucket, counter) of a stream (or table) of records; counts of records and sub-values share the state.

    ``by``: expressions such as a window to keep one sketch for each.  ``weight``: +1 or -1 per record;
    with retractions the counters are those of the net records.
    """
    names = [f"k{i}" for i in range(len(by))]
    more = ["_w"] if weight else []
    keyed = df.select(record_id, *attrs, *[c.alias(n) for c, n in zip(by, names)], *([F.col(weight).alias("_w")] if weight else []))
    up = sketch.updates(subvalues.level_stream(keyed, attrs, spec, record_id, True, [*names, *more]), spec, [*names, *more])
    signed = F.col("sign") * F.col("_w") if weight else F.col("sign")
    return up.groupBy(*names, "level", "row", "bucket").agg(F.sum(signed).alias("counter"))


def event_time(df: DataFrame, ts: str, lateness: str) -> DataFrame:
    """``df`` with a watermark; a time without zone becomes a timestamp of the session's zone first."""
    kind = dict(df.dtypes)[ts]
    return (df.withColumn(ts, F.col(ts).cast("timestamp")) if kind != "timestamp" else df).withWatermark(ts, lateness)


def tumbling(df: DataFrame, attrs: Sequence[str], spec: EstimatorSpec, record_id: str, ts: str, size: str) -> DataFrame:
    """One sketch per window of ``size``."""
    return sketch_stream(df, attrs, spec, record_id, [F.window(ts, size)])


def sliding_from_panes(panes: DataFrame, panes_per_window: int, size_seconds: int) -> DataFrame:
    """Sketches of sliding windows from those of their panes: each pane's counters are added to the windows that hold it, so records are not copied."""
    start = F.explode(F.sequence(F.lit(0), F.lit(panes_per_window - 1)))
    shifted = panes.withColumn("back", start).withColumn("start", (F.col("k0.start").cast("long") - F.col("back") * size_seconds).cast("timestamp"))
    return shifted.groupBy("start", "level", "row", "bucket").agg(F.sum("counter").alias("counter"))


def sessions(df: DataFrame, user: str, ts: str, gap: str) -> DataFrame:
    """(user, start, first_type, n_events, day) of each session, records for a profile over sessions."""
    got = df.groupBy(F.col(user), F.session_window(ts, gap).alias("w")).agg(F.min(F.struct(ts, "event_type")).alias("f"), F.count(F.lit(1)).alias("n_events"))
    return got.select(user, F.col("w.start").alias("start"), F.col("f.event_type").alias("first_type"), "n_events", F.to_date("w.start").alias("day"))


def finalizer(d: int, spec: EstimatorSpec, sink: Callable[[DataFrame, int], None]) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: turns the counters of a complete-mode batch, a few thousand rows, into a profile."""
    return lambda counters, batch: sink(estimate.from_sketch(counters, d, spec), batch)


def start_profile(df: DataFrame, attrs: Sequence[str], spec: EstimatorSpec, record_id: str, sink: Callable[[DataFrame, int], None], checkpoint: str, trigger: dict | None = None):
    """A continuous query that hands a profile of the stream so far to ``sink`` after each micro-batch."""
    counters = sketch_stream(df, attrs, spec, record_id)
    writer = counters.writeStream.outputMode("complete").option("checkpointLocation", checkpoint).foreachBatch(finalizer(len(attrs), spec, sink))
    return writer.trigger(**(trigger or {"availableNow": True})).start()


def sample_stream(df: DataFrame, size: int, seed: int, record_id: str, store: str, checkpoint: str):
    """Pair-sampling baseline on a stream: each micro-batch merges its records of least hash into the sample kept under ``store``.

    A batch reads what the one before wrote and writes its own folder, so a restart goes on from there
    and a batch that runs again counts once.  :func:`stored_sample` reads the result.
    """
    h = F.xxhash64(F.lit(seed), F.col(record_id))

    def merge(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        rows, n = batch.withColumn("_h", h), batch.agg(F.count(F.lit(1)).alias("n"))
        if number:
            before = spark.read.schema(rows.schema).parquet(f"{store}/{number - 1}/sample")
            rows, n = rows.unionByName(before), n.unionByName(spark.read.schema("n long").parquet(f"{store}/{number - 1}/n"))
        rows.orderBy("_h", record_id).limit(size).write.mode("overwrite").parquet(f"{store}/{number}/sample")
        n.agg(F.sum("n").alias("n")).write.mode("overwrite").parquet(f"{store}/{number}/n")

    return df.writeStream.foreachBatch(merge).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def stored_sample(spark: SparkSession, store: str, number: int) -> tuple[DataFrame, int]:
    """The sample after micro-batch ``number`` and the records seen until then."""
    return spark.read.parquet(f"{store}/{number}/sample").drop("_h"), spark.read.parquet(f"{store}/{number}/n").first()[0]
