"""Sketches and exact moments of repeated draws: what depends on a record is made once, what depends on a seed in numpy.

A record's fingerprints are the same for all seeds; the draws and the hashes of the counters are not.
Equal fingerprints of a batch are hashed once for each seed.  The counters are those of
:func:`pairlattice.operators.sketch.updates` over the level stream of each seed, the moments those of
:func:`pairlattice.operators.moments.level_moments`: a sub-value is shuffled once, with the seeds that draw it.
"""

from __future__ import annotations

import math
import struct
from collections.abc import Iterator, Sequence
from functools import reduce
from math import comb

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairlattice.functions.hashing import coefficients
from pairlattice.lattice import masks, subsets
from pairlattice.operators.records import canonicalized
from pairlattice.operators.subvalues import TOP, cells, fingerprint
from pairlattice.spec import EstimatorSpec

P1, P2, P3, P4, P5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))
MERSENNE, BITS = np.uint64((1 << 31) - 1), np.uint64(31)
#: Records that are worked on at once.
ROWS = 16_384
#: Sub-values that are counted at once, seeds whose draws share a word, and equal sub-values of a batch from which on they are sent as counts.
VALUES, SEEDS, MANY = 1 << 20, 62, 16


def fits(df: DataFrame, spec: EstimatorSpec, record_id: str) -> bool:
    return spec.sampler == "fixed" and spec.fingerprint == "xx64" and spec.kind == "fast" and dict(df.dtypes)[record_id] in ("bigint", "int")


def turned(x: np.ndarray, by: int) -> np.ndarray:
    return x << np.uint64(by) | x >> np.uint64(64 - by)


def mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ h >> np.uint64(33)) * P2
    h = (h ^ h >> np.uint64(29)) * P3
    return h ^ h >> np.uint64(32)


def hash_int(value: np.ndarray, seed: np.ndarray) -> np.ndarray:
    """xxHash64 of 32-bit integers, as Spark's."""
    return mixed(turned(seed + (P5 + np.uint64(4)) ^ value * P1, 23) * P2 + P3)


def hash_long(value: np.ndarray, seed: np.ndarray) -> np.ndarray:
    return mixed(turned(seed + (P5 + np.uint64(8)) ^ turned(value * P2, 31) * P1, 27) * P1 + P4)


def started(seed: int, what: str) -> np.ndarray:
    """The hash of a seed and a word, which that of the record goes on from."""
    return np.array([xxhash.xxh64_intdigest(what.encode(), seed=xxhash.xxh64_intdigest(struct.pack("<i", seed), seed=42))], np.uint64)


def polynomial(c: list[int], x: np.ndarray) -> np.ndarray:
    """A cubic modulo 2^31 - 1, reduced below 2^33 only."""
    out = x * np.uint64(c[0]) + np.uint64(c[1])
    for a in c[2:]:
        out = (out & MERSENNE) + (out >> BITS)
        out *= x
        out += np.uint64(a)
    return (out & MERSENNE) + (out >> BITS)


def hashed(c: list[list[int]], parts: Sequence[np.ndarray]) -> np.ndarray:
    return (polynomial(c[0], parts[0]) + polynomial(c[1], parts[1]) + polynomial(c[2], parts[2])) % MERSENNE


def drawn(rid: np.ndarray, whole: np.ndarray | None, wide: bool, d: int, level: int, spec: EstimatorSpec, begin: dict[str, np.ndarray]) -> np.ndarray | None:
    """(records, subsets) whether a record emits a subset of ``level``; none where all are."""
    want = spec.ratio_of(level) * comb(d, level)
    low = math.floor(want + 1e-12)
    extra = want - low
    if low == comb(d, level):
        return None
    go_on = hash_long if wide else hash_int

    def draw(what: str, keys: Sequence[int]) -> np.ndarray:
        h = go_on(rid, begin[what])
        if whole is not None:
            h = np.where(whole, begin[what], h)
        return np.stack([hash_int(np.array([k], np.uint64), h) for k in keys], 1) & np.uint64(TOP - 1)

    h = draw("m", subsets(d, level))
    count = np.full(len(rid), low) + (draw("n", [level])[:, 0] < np.uint64(int(extra * TOP)) if extra > 1e-12 else 0)
    last = np.sort(h, 1)[np.arange(len(h)), np.maximum(count - 1, 0)]  # two draws of a record are equal with a chance of 2^-60
    return (h <= last[:, None]) & (count > 0)[:, None]


def fingerprinted(df: DataFrame, attrs: Sequence[str], spec: EstimatorSpec, record_id: str) -> DataFrame:
    """(rid, missing, f..): the fingerprints of all subsets of a record, and the bits of its null attributes where these count."""
    d, spark = len(attrs), df.sparkSession
    base = canonicalized(df.select(record_id, *attrs), attrs, record_id, spec.null_policy)
    base = base.repartition(max(spark.sparkContext.defaultParallelism, base.rdd.getNumPartitions()))  # few bytes, much work
    missing = sum((F.when(F.isnull(f"a{i + 1}"), F.lit(1 << i)).otherwise(F.lit(0)) for i in range(d)), F.lit(0)) if spec.null_policy == "never" else F.lit(0)
    base = base.select("rid", missing.alias("missing"), *[c.alias(f"c{i + 1}") for i, c in enumerate(cells(base, d, spec))])
    return base.select("rid", "missing", *[fingerprint(F.lit(m), d, spec).alias(f"f{m}") for m in masks(d, spec.s)])


def gathered(batches: Iterator[pa.RecordBatch], rows: int = ROWS) -> Iterator[pa.Table]:
    held, n = [], 0
    for b in batches:
        held.append(b)
        n += len(b)
        if n >= rows:
            yield pa.Table.from_batches(held)
            held, n = [], 0
    if held:
        yield pa.Table.from_batches(held)


def identities(t: pa.Table, wide: bool) -> tuple[np.ndarray, np.ndarray | None, np.ndarray | None]:
    """Ids as they are hashed, which of them are null, and the null attributes if there are any."""
    column = t.column(0).combine_chunks()
    whole = column.is_null().to_numpy(zero_copy_only=False) if column.null_count else None
    rid = column.fill_null(0).to_numpy()
    absent = t.column(1).to_numpy()
    return rid.view(np.uint64) if wide else rid.view(np.uint32).astype(np.uint64), whole, absent if absent.any() else None


def moments(df: DataFrame, attrs: Sequence[str], spec: EstimatorSpec, record_id: str, seeds: Sequence[int]) -> DataFrame:
    """(seed, level, y, emitted) of the level streams of all seeds, with level 0: exact."""
    seeds = [int(k) for k in seeds]
    parts = [_moments(df, attrs, spec, record_id, seeds[i : i + SEEDS]) for i in range(0, len(seeds), SEEDS)]
    return reduce(DataFrame.unionByName, parts)


def _moments(df: DataFrame, attrs: Sequence[str], spec: EstimatorSpec, record_id: str, seeds: list[int]) -> DataFrame:
    d, wide = len(attrs), dict(df.dtypes)[record_id] == "bigint"
    levels, every = range(spec.s, d + 1), masks(d, spec.s)
    span = {k: (every.index(subsets(d, k)[0]), comb(d, k)) for k in levels}
    begin = {k: {w: started(k, w) for w in ("m", "n")} for k in seeds}
    rows = max(ROWS, VALUES // len(every))
    names = ["fp", "mask", "drawn", "counts"]

    def batch(fp: np.ndarray, mask: np.ndarray, drawn_by: np.ndarray, counts: np.ndarray | None) -> pa.RecordBatch:
        """Sub-values with the seeds that drew them as bits, or, of many equal ones, the number for each seed."""
        if counts is None:
            held = pa.nulls(len(fp), pa.binary())
        else:
            ends = np.arange(len(fp) + 1, dtype=np.int32) * np.int32(8 * len(seeds))
            held = pa.Array.from_buffers(pa.binary(), len(fp), [None, pa.py_buffer(ends), pa.py_buffer(np.ascontiguousarray(counts, np.int64))])
        return pa.RecordBatch.from_arrays([pa.array(fp, pa.int64()), pa.array(mask, pa.int32()), pa.array(drawn_by.view(np.int64), pa.int64()), held], names=names)

    def emitted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in gathered(batches, rows):
            rid, whole, absent = identities(t, wide)
            yield batch(np.zeros(1, np.int64), np.zeros(1, np.int32), np.zeros(1, np.uint64), np.full((1, len(seeds)), len(rid)))
            for j in levels:
                at, width = span[j]
                bits = np.zeros((len(rid), width), np.uint64)
                for i, k in enumerate(seeds):
                    chosen = drawn(rid, whole, wide, d, j, spec, begin[k])
                    bits |= np.uint64(1 << i) if chosen is None else chosen.astype(np.uint64) << np.uint64(i)
                for i in range(width):
                    fp, b, mask = t.column(2 + at + i).to_numpy(), bits[:, i], every[at + i]
                    some = b != 0 if absent is None else (b != 0) & (absent & mask == 0)
                    fp, b = fp[some], b[some]
                    order = np.argsort(fp)
                    fp, b = fp[order], b[order]
                    starts = np.flatnonzero(np.r_[True, fp[1:] != fp[:-1]][: len(fp)])
                    size = np.diff(np.r_[starts, len(fp)])
                    hot = size > MANY
                    few = ~np.repeat(hot, size)
                    if few.any():
                        yield batch(fp[few], np.full(int(few.sum()), mask, np.int32), b[few], None)
                    if hot.any():
                        b, begins = b[~few], np.r_[0, np.cumsum(size[hot])[:-1]]
                        counts = np.stack([np.add.reduceat(b >> np.uint64(q) & np.uint64(1), begins) for q in range(len(seeds))], 1)
                        yield batch(fp[starts[hot]], np.full(len(begins), mask, np.int32), np.zeros(len(begins), np.uint64), counts)

    def squared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[int, list[list[int]]] = {}
        place = np.arange(len(seeds), dtype=np.uint64)

        def add(t: pa.Table) -> None:
            fp, mask, bits = t.column(0).to_numpy(), t.column(1).to_numpy(), t.column(2).to_numpy().view(np.uint64)
            held = t.column(3).combine_chunks()
            many = held.is_valid().to_numpy(zero_copy_only=False)
            starts = np.flatnonzero(np.r_[True, (fp[1:] != fp[:-1]) | (mask[1:] != mask[:-1])])
            level = np.bitwise_count(mask[starts]).astype(int)
            c = (bits[:, None] >> place & np.uint64(1)).astype(np.int64)
            if many.any():
                c[many] = np.frombuffer(b"".join(held.filter(pa.array(many)).to_pylist()), np.int64).reshape(-1, len(seeds))
            c = np.add.reduceat(c, starts, axis=0)
            if c.max() >= 1 << 20:  # sums of squares beyond 63 bits
                c = c.astype(object)
            for j in np.unique(level):
                of = c[level == j]
                y, n = total.setdefault(int(j), [[0] * len(seeds), [0] * len(seeds)])
                y[:], n[:] = [a + int(b) for a, b in zip(y, (of * of).sum(0))], [a + int(b) for a, b in zip(n, of.sum(0))]

        rest = None
        for t in gathered(batches, 1 << 17):
            t = t if rest is None else pa.concat_tables([rest, t])
            fp, mask = t.column(0).to_numpy(), t.column(1).to_numpy()
            other = np.flatnonzero((fp != fp[-1]) | (mask != mask[-1]))
            cut = int(other[-1]) + 1 if len(other) else 0  # the last value may go on
            if cut:
                add(t.slice(0, cut))
            rest = t.slice(cut)
        if rest is not None:
            add(rest)
        out = [(k, j, str(y[i]), n[i]) for j, (y, n) in total.items() for i, k in enumerate(seeds) if n[i]]
        if out:
            kinds = (pa.int32(), pa.int32(), pa.string(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out), kinds)], names=["seed", "level", "y", "emitted"])

    stream = fingerprinted(df, attrs, spec, record_id).mapInArrow(emitted, "fp long, mask int, drawn long, counts binary")
    each = stream.repartition("fp").sortWithinPartitions("fp", "mask").mapInArrow(squared, "seed int, level int, y string, emitted long")
    out = each.groupBy("seed", "level").agg(F.sum(F.col("y").cast("decimal(38,0)")).cast("decimal(38,0)").alias("y"), F.sum("emitted").alias("emitted"))
    return df.sparkSession.createDataFrame(out.collect(), out.schema)  # seeds x levels rows, made once for all that read them


def counters(df: DataFrame, attrs: Sequence[str], spec: EstimatorSpec, record_id: str, seeds: Sequence[int]) -> DataFrame:
    """(seed, level, row, bucket, counter) of the sketches of all seeds."""
    d, seeds = len(attrs), [int(k) for k in seeds]
    wide = dict(df.dtypes)[record_id] == "bigint"
    levels = range(spec.s, d + 1)
    every = masks(d, spec.s)
    span = {k: (every.index(subsets(d, k)[0]), comb(d, k)) for k in levels}
    begin = {k: {w: started(k, w) for w in ("m", "n")} for k in seeds}
    coef = {k: [(coefficients(k, r, "sign"), coefficients(k, r, "bucket")) for r in range(spec.depth)] for k in seeds}
    base = fingerprinted(df, attrs, spec, record_id)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = {(k, j): np.zeros((spec.depth, spec.width), np.int64) for k in seeds for j in levels}
        size = dict.fromkeys([(k, j) for k in seeds for j in (0, *levels)], 0)
        for t in gathered(batches):
            rid, whole, absent = identities(t, wide)
            for k in seeds:
                size[k, 0] += len(rid)
            for j in levels:
                at, width = span[j]
                fp = np.stack([t.column(2 + at + i).to_numpy() for i in range(width)], 1).view(np.uint64) & np.uint64(TOP - 1)
                usable = None if absent is None else np.stack([absent & m == 0 for m in every[at : at + width]], 1)
                values, place = np.unique(fp, return_inverse=True)
                place = place.reshape(fp.shape)
                low, high = values & np.uint64((1 << 30) - 1), values >> np.uint64(30)
                parts = np.stack([low, high, (low + high) % MERSENNE])
                same: tuple | None = None
                for k in seeds:
                    chosen = drawn(rid, whole, wide, d, j, spec, begin[k])
                    chosen = usable if chosen is None else chosen if usable is None else chosen & usable
                    if chosen is None and same:
                        weight, some = same
                    else:
                        weight = np.bincount(place.ravel() if chosen is None else place[chosen], minlength=len(values))
                        some = np.flatnonzero(weight)
                        weight = weight[some]
                        same = (weight, some) if chosen is None else None
                    size[k, j] += int(weight.sum())
                    x = parts if len(some) == len(values) else parts[:, some]
                    for r, (sign, bucket) in enumerate(coef[k]):
                        signed = np.where(hashed(sign, x) & np.uint64(1), weight, -weight)
                        to = (hashed(bucket, x) % np.uint64(spec.width)).astype(np.int64)
                        total[k, j][r] += np.bincount(to, signed, spec.width).astype(np.int64)
        for k in seeds:
            parts = [(np.int32(j), np.array([-1]), np.array([0]), np.array([size[k, j]])) for j in (0, *levels) if size[k, j]]
            for j in levels:
                r, b = np.nonzero(total[k, j])
                parts.append((np.int32(j), r, b, total[k, j][r, b]))
            if parts:
                level = np.concatenate([np.full(len(p[1]), p[0], np.int32) for p in parts])
                row, bucket, counter = (np.concatenate([p[i] for p in parts]) for i in (1, 2, 3))
                key = (level.astype(np.int64) * (spec.depth + 1) + row + 1) * spec.width + bucket
                columns = [pa.array(np.full(len(level), k, np.int32)), pa.array(key), pa.array(level), pa.array(row.astype(np.int32)), pa.array(bucket.astype(np.int32)), pa.array(counter.astype(np.int64))]
                yield pa.RecordBatch.from_arrays(columns, names=["seed", "key", "level", "row", "bucket", "counter"])

    # grouped by one key, so that no condition on a row or level moves below the sum and Spark makes it once for all that read it
    part = base.mapInArrow(run, "seed int, key long, level int, row int, bucket int, counter long")
    out = part.groupBy("seed", "key").agg(*[F.max(c).alias(c) for c in ("level", "row", "bucket")], F.sum("counter").alias("counter"))
    return out.select("seed", "level", "row", "bucket", "counter")
