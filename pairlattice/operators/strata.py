"""Pairs drawn from LSH strata where the records, packed into a few words each, fit every task.

The attributes become numbers of a dictionary, packed side by side; two records agree on an attribute
where the bits of its field are equal.  Packed records are broadcast in the order of their hashes;
a task sorts them by bucket once, makes the draws of its range of ids in numpy, and sends only the
number of pairs of each level.  The draws are those of :func:`pairlattice.operators.baselines.lsh_strata`.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pairlattice.operators.repeats import P1, P2, P4, P5, gathered, hash_int, hash_long, mixed, started, turned

#: Bytes of the packed records and different values of all attributes that a task holds; beyond them records are joined.
MOST_BYTES, MOST_VALUES = 80 << 20, 4 << 20
#: Draws that are made at once, and the most of a task.
BLOCK, TASK = 1 << 15, 1 << 28
LONG = P5 + np.uint64(8)
#: Draws by MD5 that are made at once: their last four digits.
DIGITS = 10_000


@dataclass
class Packed:
    """Records in the order of their hashes."""

    n: int
    words: list[np.ndarray]
    #: (word, shift, bits) of each attribute
    fields: list[tuple[int, int, int]]
    #: hashes of the values of each attribute, by their number
    values: list[np.ndarray]
    #: the buckets of the records for each choice of columns, where they cannot be made from the hashes
    buckets: dict[int, np.ndarray]


def packed(base: DataFrame, d: int, order: Column, buckets: dict[int, Column]) -> Packed | None:
    """The records of ``base``; none if they are too many."""
    spark = base.sparkSession
    base = base.select(order.alias("h"), *[F.xxhash64(F.isnull(f"a{i}"), F.col(f"a{i}")).alias(f"c{i}") for i in range(1, d + 1)], *[b.alias(f"b{m}") for m, b in buckets.items()])
    each = base.select(F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.col(f"c{i + 1}").alias("v")) for i in range(d)])).alias("x"))
    known = each.groupBy("x.i", "x.v").agg(F.count(F.lit(1)).alias("c")).limit(MOST_VALUES + 1).toArrow()
    if len(known) > MOST_VALUES:
        return None
    attribute, value = known["i"].to_numpy(), known["v"].to_numpy()
    n = int(known["c"].to_numpy()[attribute == 0].sum())
    values = [np.sort(value[attribute == i]) for i in range(d)]
    fields, word, shift = [], 0, 0
    for v in values:
        bits = max(1, int(len(v) - 1).bit_length())
        if shift + bits > 64:
            word, shift = word + 1, 0
        fields.append((word, shift, bits))
        shift += bits
    if n == 0 or n * 8 * (word + 1 + len(buckets)) > MOST_BYTES:
        return None
    names = ["h", *[f"w{i}" for i in range(word + 1)], *[f"b{m}" for m in buckets]]
    told, extra = spark.sparkContext.broadcast(values), len(buckets)

    def coded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in gathered(batches):
            words = [np.zeros(len(t), np.uint64) for _ in range(word + 1)]
            for i, (w, s, _) in enumerate(fields):
                words[w] |= np.searchsorted(told.value[i], t.column(1 + i).to_numpy()).astype(np.uint64) << np.uint64(s)
            more = [t.column(1 + d + i).to_numpy() for i in range(extra)]
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in (t.column(0).to_numpy(), *[x.view(np.int64) for x in words], *more)], names=names)

    got = base.mapInArrow(coded, ", ".join(f"{c} long" for c in names)).toArrow()
    at = np.argsort(got["h"].to_numpy(), kind="stable")
    column = lambda c: got[c].to_numpy()[at]
    narrow = word == 0 and shift <= 32
    out = Packed(n, [column(f"w{i}").view(np.uint64).astype(np.uint32 if narrow else np.uint64, copy=False) for i in range(word + 1)], fields, values, {m: column(f"b{m}") for m in buckets})
    told.destroy()
    return out


class Order:
    """The records of a table by their buckets for one choice of columns (bit i: attribute i)."""

    def __init__(self, p: Packed, mask: int):
        bucket = p.buckets.get(mask)
        if bucket is None:
            bucket = np.empty(p.n, np.uint64)
            begin = hash_int(np.array([mask], np.uint64), np.array([42], np.uint64))
            for lo in range(0, p.n, 1 << 18):
                h = begin
                for i, (w, s, bits) in enumerate(p.fields):
                    if mask >> (i + 1) & 1:
                        number = p.words[w][lo : lo + (1 << 18)].astype(np.uint64) >> np.uint64(s) & np.uint64((1 << bits) - 1)
                        h = hash_long(p.values[i][number].view(np.uint64), h)
                bucket[lo : lo + (1 << 18)] = h
            bucket = bucket.view(np.int64)
        at = np.argsort(bucket, kind="stable")
        bucket = bucket[at]
        self.words = [w[at] for w in p.words]
        self.n = p.n
        starts = np.flatnonzero(np.r_[True, bucket[1:] != bucket[:-1]])
        self.buckets = len(starts)
        size = np.diff(np.r_[starts, p.n])
        pairs = size * (size - 1) // 2
        self.high = int(pairs.sum())
        some = pairs > 0
        self.starts, self.ends = starts[some], np.cumsum(pairs[some])
        self.begins = self.ends - pairs[some]
        same = [(w, self.words[w].dtype.type(((1 << bits) - 1) << s)) for w, s, bits in p.fields]
        self.fields, self.shared = same, [f for i, f in enumerate(same) if mask >> (i + 1) & 1]

    def levels(self, l: np.ndarray, r: np.ndarray, apart: bool) -> np.ndarray:
        """How many pairs agree on 0..d attributes; ``apart``: of those in different buckets."""
        unlike = [w.take(l, mode="clip") ^ w.take(r, mode="clip") for w in self.words]
        level = np.zeros(len(l), np.uint8)
        for w, m in self.fields:
            level += unlike[w] & m == 0
        out = np.array([np.count_nonzero(level == k) for k in range(len(self.fields) + 1)])
        if apart:
            near = np.ones(len(l), bool)
            for w, m in self.shared:
                near &= unlike[w] & m == 0
            out -= np.bincount(level[near], minlength=len(out))
        return out

    def within(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The records of pairs in one bucket: row a of a bucket has its pairs a(a-1)/2 .. a(a+1)/2 - 1."""
        b = np.searchsorted(self.ends, at, "right")
        o = at - self.begins[b]
        a = np.floor((np.sqrt(8.0 * o + 1) + 1) / 2).astype(np.int64)
        a -= a * (a - 1) // 2 > o
        a += a * (a + 1) // 2 <= o
        return self.starts[b] + a, self.starts[b] + o - a * (a - 1) // 2


def remainders(x: np.ndarray, total: int) -> np.ndarray:
    """``x`` modulo ``total``, not negative; by a division of numpy's fast kind."""
    return x - x // np.int64(total) * np.int64(total)


# ---- MD5 ------------------------------------------------------------------------------------

_TURNS = [t for turns in ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)) for _ in range(4) for t in turns]
_CONSTANTS = [int(abs(np.sin(np.float64(i + 1))) * 2**32) for i in range(64)]
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)


def leading_60(prefix: bytes, first: int, count: int) -> np.ndarray:
    """:func:`pairlattice.functions.hashing.md5_60` of ``prefix`` and each number from ``first`` on; at most DIGITS numbers, of equal leading digits."""
    if first < DIGITS or len(prefix) > 30:
        return np.array([int.from_bytes(hashlib.md5(prefix + str(i).encode()).digest()[:8], "big") >> 4 for i in range(first, first + count)], np.int64)
    head, low = divmod(first, DIGITS)
    text = prefix + str(head).encode()
    last = np.arange(low, low + count, dtype=np.uint32)
    fixed = bytearray(64)
    fixed[: len(text)] = text
    fixed[len(text) + 4] = 0x80
    fixed[56:64] = (8 * (len(text) + 4)).to_bytes(8, "little")
    words: list = list(np.frombuffer(bytes(fixed), "<u4"))
    for i in range(4):
        w, byte = divmod(len(text) + i, 4)
        digit = (last // np.uint32(10 ** (3 - i)) % np.uint32(10) + np.uint32(48)) << np.uint32(8 * byte)
        words[w] = words[w] | digit
    a, b, c, d = (np.full(count, x, np.uint32) for x in _START)
    f, t = np.empty(count, np.uint32), np.empty(count, np.uint32)
    for i in range(64):
        if i < 16:
            g = i
            np.bitwise_xor(c, d, out=f)
            f &= b
            f ^= d
        elif i < 32:
            g = (5 * i + 1) % 16
            np.bitwise_xor(b, c, out=f)
            f &= d
            f ^= c
        elif i < 48:
            g = (3 * i + 5) % 16
            np.bitwise_xor(b, c, out=f)
            f ^= d
        else:
            g = 7 * i % 16
            np.invert(d, out=f)
            f |= b
            f ^= c
        f += a
        if isinstance(words[g], np.ndarray):
            f += words[g]
            f += np.uint32(_CONSTANTS[i])
        else:
            f += np.uint32((int(words[g]) + _CONSTANTS[i]) & 0xFFFFFFFF)
        np.left_shift(f, np.uint32(_TURNS[i]), out=t)
        f >>= np.uint32(32 - _TURNS[i])
        f |= t
        f += b
        a, d, c, b, f = d, c, b, f, a  # the old a is overwritten next
    a, b = a + np.uint32(_START[0]), b + np.uint32(_START[1])
    return (a.byteswap().astype(np.int64) << 28) | (b.byteswap() >> np.uint32(4)).astype(np.int64)


# ---- draws ----------------------------------------------------------------------------------


def blocks(lo: int, hi: int, oracle: bool) -> Iterator[tuple[int, int]]:
    step = DIGITS if oracle else BLOCK
    while lo < hi:
        end = min(hi, lo - lo % step + step)
        yield lo, end
        lo = end


def counted(o: Order, seed: int, stratum: str, lo: int, hi: int, oracle: bool) -> np.ndarray:
    """Pairs by level of the draws ``lo`` .. ``hi`` - 1 of a stratum."""
    total = np.zeros(len(o.fields) + 1, np.int64)
    begin = {w: started(seed, w) + LONG for w in "hlr"}

    def draws(a: int, b: int, *wanted: tuple[str, int]) -> list[np.ndarray]:
        """Numbers below the given totals, of the ids ``a`` .. ``b`` - 1."""
        if oracle:
            return [remainders(leading_60(f"{what}{seed}|".encode(), a, b - a), of) for what, of in wanted]
        ids = turned(np.arange(a, b, dtype=np.uint64) * P2, 31) * P1  # hash_long, with what depends on the id made once
        return [remainders(mixed(turned(begin[what] ^ ids, 27) * P1 + P4).view(np.int64), of) for what, of in wanted]

    for a, b in blocks(lo, hi, oracle):
        if stratum == "high":
            total += o.levels(*o.within(*draws(a, b, ("h", o.high))), False)
        else:
            total += o.levels(*draws(a, b, ("l", o.n), ("r", o.n)), True)
    return total


def in_tasks(spark: SparkSession, tasks: list, run: Callable, schema: str) -> list:
    """The rows that ``run`` makes of each task."""

    names = [c.split()[0] for c in schema.split(", ")]
    kinds = [{"int": pa.int32(), "long": pa.int64(), "string": pa.string()}[c.split()[1]] for c in schema.split(", ")]

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = [r for i in b.column(0).to_pylist() for r in run(tasks[i])]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(zip(*rows), kinds)], names=names)

    return spark.range(0, len(tasks), 1, len(tasks)).mapInArrow(go, schema).collect() if tasks else []


def sizes(spark: SparkSession, held: Broadcast, masks: Sequence[int]) -> dict[int, tuple[int, int]]:
    """For each choice of columns the pairs within buckets, and the buckets."""

    def one(mask: int) -> list[tuple]:
        o = Order(held.value, mask)
        return [(mask, o.high, o.buckets)]

    return {r["mask"]: (r["high"], r["buckets"]) for r in in_tasks(spark, list(masks), one, "mask int, high long, buckets long")}


def hits(spark: SparkSession, held: Broadcast, wanted: Sequence[tuple[int, int, int, int]], oracle: bool) -> list[tuple[int, int, int, str]]:
    """(seed, level, hits, stratum) of (seed, columns, draws within, draws across)."""
    ranges = sorted((mask, seed, what, n) for seed, mask, high, low in wanted for what, n in (("high", high), ("low", low)) if n)
    share = min(TASK, max(1 << 20, sum(r[3] for r in ranges) // (4 * spark.sparkContext.defaultParallelism)))
    tasks: list[tuple[int, list]] = []
    left = 0
    for mask, seed, what, n in ranges:
        lo = 0
        while lo < n:
            if left <= 0 or tasks[-1][0] != mask:
                tasks.append((mask, []))
                left = share
            hi = min(n, lo + left)
            tasks[-1][1].append((seed, what, lo, hi))
            left -= hi - lo
            lo = hi

    def one(task: tuple[int, list]) -> list[tuple]:
        o = Order(held.value, task[0])
        found = [(seed, what, counted(o, seed, what, lo, hi, oracle)) for seed, what, lo, hi in task[1]]
        return [(seed, level, int(c), what) for seed, what, counts in found for level, c in enumerate(counts) if c]

    total: dict[tuple[int, int, str], int] = {}
    for r in in_tasks(spark, tasks, one, "seed int, level int, hits long, stratum string"):
        key = r["seed"], r["level"], r["stratum"]
        total[key] = total.get(key, 0) + r["hits"]
    return [(k, j, c, what) for (k, j, what), c in total.items()]
