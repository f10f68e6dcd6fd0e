"""Near-duplicate classes by order MinHash over word shingles, verified by banded alignment.

Each shingle of five words is labelled with its occurrence number.  For each of ``slots`` hash
functions the ``order`` least labelled shingles are taken and put back in text order; their joint
hash is one signature, so two texts agree on it with a chance that falls with their edit distance,
not only with what they share.  Texts with an equal signature in a slot are candidates; a candidate
pair is linked when the word-level edit distance is at most (1 - similarity) of the longer text.
Classes are the connected components of the links.

The number of slots follows from ``recall``, by the mean share of shingles that survive, so that what is
measured lies somewhat lower (README): the chance that a pair at exactly ``similarity``, with edits
scattered over a long text, shares a slot.  Such edits can leave short texts no two common shingles, so
texts of at most ``short`` words also meet without chance: with at most e edits, one of e + 1 equal
pieces of the longer text stands whole in the other, shifted by at most e words.  Pieces are buckets
like those of the slots.

First every text is compared with one text that leads one of its buckets, then in two rounds a text
of every class of a bucket with one of its first class; both are linear in the buckets.  In buckets
whose texts are still in several classes, all pairs of different classes that fit in length are
compared too, each in its first common slot, which is told by 32 bits of each signature.  Counts of
the words by 64 classes of hashes bound the distance from below before words are looked at.  Pairs are
aligned inside the task, so only links become rows.  Large buckets are cut into blocks and dealt as pairs of
blocks, so no task holds more than two blocks and no pair is left out.

Nodes are texts, named by a 64-bit hash; the class id is the least document id of the class.

Defined results: equal texts form one class whatever their number; null and word-less texts stand
alone; a text of fewer than five words is one shingle; repeated rows, and several texts under one id,
get a row each; a null id comes after all others, so a class has a null id only if no text of it has
another; further columns are ignored; an empty table gives no rows.  Of millions of texts a
pair with equal hashes has a chance of about 10^-7 to exist at all.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairlattice.llm.common import Workspace, cut, tidy, unused
from pairlattice.llm.components import components

PRIME = np.uint64(0x9E3779B97F4A7C15)
MIX = np.uint64(0xD6E8FEB86659FD93)


@dataclass(frozen=True)
class Settings:
    shingle: int = 5
    order: int = 2
    #: Chance that a pair at exactly ``similarity`` becomes a candidate, which sets the slots; texts of up to ``short`` words do without chance.
    recall: float = 0.95
    short: int = 24
    similarity: float = 0.8
    seed: int = 5
    #: Rounds that compare classes by a text of each, before all pairs of different classes are compared.
    class_rounds: int = 2
    #: Texts of a block of a large bucket.
    block: int = 4096

    @property
    def slots(self) -> int:
        """Slots for ``recall``: of n shingles n * similarity ** shingle survive, and a slot agrees with their Jaccard similarity to the power ``order``."""
        survive = self.similarity**self.shingle
        return math.ceil(math.log(1 - self.recall) / math.log(1 - (survive / (2 - survive)) ** self.order))

    def edits(self, n_words: int) -> int:
        """Edits that a pair whose longer text has this many words may have."""
        return int((1 - self.similarity) * n_words + 1e-9)


class WordHash(dict):
    """64-bit hash of a word; forgets when full."""

    def __missing__(self, word: str) -> int:
        if len(self) > 500_000:
            self.clear()
        h = self[word] = xxhash.xxh3_64_intdigest(word.encode("utf-8", "surrogatepass"))
        return h

    def of(self, words: list[str]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * MIX
    return x ^ (x >> np.uint64(29))


def labelled(words: np.ndarray, size: int) -> np.ndarray:
    """Hashes of the shingles with their occurrence numbers, in text order; all differ."""
    k = min(size, len(words))
    n = len(words) - k + 1
    h = np.zeros(n, np.uint64)
    for j in range(k):
        h = h * PRIME + words[j : j + n]
    h = mix(h)
    order = np.argsort(h, kind="stable")
    s = h[order]
    new = np.ones(n, bool)
    new[1:] = s[1:] != s[:-1]
    occurrence = np.zeros(n, np.uint64)
    if not new.all():
        start = np.maximum.accumulate(np.where(new, np.arange(n), 0))
        occurrence[order] = (np.arange(n) - start).astype(np.uint64)
    return mix(h + occurrence * PRIME)


def signature(words: np.ndarray, settings: Settings, seeds: np.ndarray, odd: np.ndarray) -> np.ndarray:
    """One 64-bit value per slot."""
    h = labelled(words, settings.shingle)
    order, out = min(settings.order, len(h)), np.zeros(settings.slots, np.uint64)
    step = max(1, (1 << 20) // len(h))
    for lo in range(0, settings.slots, step):
        v = (h[None, :] ^ seeds[lo : lo + step, None]) * odd[lo : lo + step, None]
        rows, picked = np.arange(len(v)), []
        for _ in range(order):
            at = v.argmin(1)
            picked.append(at)
            v[rows, at] = np.uint64(0xFFFFFFFFFFFFFFFF)
        for at in np.sort(np.stack(picked), 0):
            out[lo : lo + step] = mix(out[lo : lo + step] * PRIME + h[at])
    return out


def constants(settings: Settings) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(settings.seed)
    draw = lambda: rng.integers(0, 2**63, settings.slots, np.int64).astype(np.uint64) * np.uint64(2)
    return draw(), draw() | np.uint64(1)


def pieces(words: np.ndarray, settings: Settings) -> np.ndarray:
    """Keys of a short text; two short texts that are similar enough share one.

    A key is the length of the longer text, the number of a piece of it and the words of the piece.  A
    text has its own pieces, and for each length of a longer text what stands near the places of those.
    """
    m, keys = len(words), set()
    if m > settings.short:
        return np.zeros(0, np.int64)
    raw, n = words.tobytes(), m
    while n <= settings.short and n - m <= settings.edits(n):
        e = settings.edits(n)
        cut = [k * n // (e + 1) for k in range(e + 2)]
        for k in range(e + 1):
            size = cut[k + 1] - cut[k]
            for at in range(max(0, cut[k] - e), min(m - size, cut[k] + e) + 1):
                keys.add(xxhash.xxh3_64_intdigest(raw[8 * at : 8 * (at + size)], (n << 8) + k))
        n += 1
    return np.array(sorted(keys), np.uint64).view(np.int64)


def bag(words: np.ndarray) -> np.ndarray:
    """Numbers of the words by the first six bits of their hashes; all zero, which bounds nothing, for a text too long for 16 bits."""
    return (np.bincount(mix(words) >> np.uint64(58), minlength=64) * (len(words) < 1 << 16)).astype("<u2")


def sketches(docs: DataFrame, settings: Settings) -> DataFrame:
    """(doc, node, n_words, sig, brief, bag) of each row; ``node`` is null for word-less texts, ``sig`` ends with the keys of short texts, ``brief`` holds 32 bits a slot."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, (seeds, odd) = WordHash(), constants(settings)
        for batch in batches:
            counts, sigs, briefs, bags = [], [], [], []
            for text in batch.column(2).to_pylist():
                w = text.split() if text else []
                counts.append(len(w))
                h = words.of(w)
                sig = signature(h, settings, seeds, odd).view(np.int64) if w else np.zeros(0, np.int64)
                sigs.append(np.concatenate([sig, pieces(h, settings)]) if w else sig)
                briefs.append((sig & 0xFFFFFFFF).astype("<u4").tobytes())
                bags.append(bag(h).tobytes())
            node = pc.if_else(pa.array([n > 0 for n in counts], pa.bool_()), batch.column(1), pa.scalar(None, pa.int64()))
            yield pa.RecordBatch.from_arrays([batch.column(0), node, pa.array(counts, pa.int32()), pa.array(sigs, pa.list_(pa.int64())), pa.array(briefs, pa.binary()), pa.array(bags, pa.binary())], names=["doc", "node", "n_words", "sig", "brief", "bag"])

    return docs.select(F.col("doc_id").cast("long").alias("doc"), F.xxhash64("text").alias("node"), "text").mapInArrow(tidy(run), "doc long, node long, n_words int, sig array<long>, brief binary, bag binary")


def banded(pairs: list[tuple[np.ndarray, np.ndarray]], band: int) -> np.ndarray:
    """Edit distances of sequences of integers by dynamic programming inside a band, many pairs at once.

    Exact where the result is at most ``band``; lengths may differ by at most ``band``.
    """
    p, width, big = len(pairs), 2 * band + 1, np.int32(1 << 28)
    n = np.array([len(a) for a, _ in pairs])
    m = np.array([len(b) for _, b in pairs])
    top = int(n.max(initial=0))
    a = np.full((p, top + 1), -1, np.int64)
    b = np.full((p, top + width + 1), -2, np.int64)
    for i, (x, y) in enumerate(pairs):
        a[i, : len(x)] = x
        y = y[: top + band + 1]
        b[i, band : band + len(y)] = y
    offsets = np.arange(-band, band + 1, dtype=np.int32)
    row = np.broadcast_to(np.where(offsets >= 0, offsets, big), (p, width)).astype(np.int32)
    out = np.full(p, big, np.int32)
    take = np.arange(p)

    def finish(i: int, row: np.ndarray) -> None:
        done = np.nonzero(n == i)[0]
        if len(done):
            out[done] = row[take[done], m[done] - i + band]

    finish(0, row)
    for i in range(1, top + 1):
        # column of offset o is word i + o; b is shifted right by the band
        cost = (b[:, i - 1 : i - 1 + width] != a[:, i - 1 : i]).astype(np.int32)
        now = row + cost
        np.minimum(now[:, :-1], row[:, 1:] + 1, out=now[:, :-1])
        row = np.minimum.accumulate(now - offsets, 1) + offsets
        finish(i, row)
    return out


class Prepared:
    """A sequence of words with its distinct words and their numbers."""

    __slots__ = ("words", "kinds", "times")

    def __init__(self, words: np.ndarray):
        self.words = words
        self.kinds, self.times = np.unique(words, return_counts=True)


def within(pairs: list[tuple[Prepared, Prepared]], similarity: float, cells: int = 1 << 18) -> np.ndarray:
    """Whether the edit distance of each pair is at most (1 - similarity) of the longer one.

    Words that one side lacks bound the distance from below; what passes is aligned in bands that
    widen until the distance fits, so close pairs cost little.
    """
    ok = np.zeros(len(pairs), bool)
    size = [(len(a.words), len(b.words)) for a, b in pairs]
    limit = np.array([int((1 - similarity) * max(n) + 1e-9) for n in size], np.int64)
    waiting: dict[int, list[int]] = {}
    for i, (a, b) in enumerate(pairs):
        if abs(size[i][0] - size[i][1]) > limit[i]:
            continue
        if size[i][0] == size[i][1] and (a.words == b.words).all():
            ok[i] = True
            continue
        at = np.minimum(np.searchsorted(b.kinds, a.kinds), len(b.kinds) - 1)
        least = max(size[i]) - int(np.minimum(a.times, b.times[at])[b.kinds[at] == a.kinds].sum())
        if least <= limit[i]:
            band = 8
            while band < 1.25 * least:
                band *= 3
            waiting.setdefault(band, []).append(i)
    while waiting:
        band = min(waiting)
        fit = sorted(waiting.pop(band), key=lambda i: size[i][0])
        step, lo = max(1, cells // (2 * band + 1)), 0
        while lo < len(fit):
            part = [i for i in fit[lo : lo + step] if size[i][0] <= 1.5 * size[fit[lo]][0] + 64]
            lo += len(part)
            for i, d in zip(part, banded([(pairs[i][0].words, pairs[i][1].words) for i in part], band)):
                if d <= band:
                    ok[i] = d <= limit[i]
                elif band < limit[i]:
                    waiting.setdefault(band * 3, []).append(i)
    return ok


def verify(edges: DataFrame, texts: DataFrame, similarity: float) -> DataFrame:
    """The edges (a, b) whose texts are close enough; ``texts`` has (node, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = WordHash()
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                part = batch.slice(lo, 256)
                left, right = ([Prepared(words.of(t.split()).view(np.int64)) for t in part.column(k).to_pylist()] for k in (2, 3))
                yield part.select([0, 1]).filter(pa.array(within(list(zip(left, right)), similarity)))

    a = texts.select(F.col("node").alias("a"), F.col("text").alias("ta"))
    b = texts.select(F.col("node").alias("b"), F.col("text").alias("tb"))
    return edges.join(b, "b").join(a, "a").select("a", "b", "ta", "tb").mapInArrow(tidy(run), "a long, b long")


def linked(mixed: DataFrame, settings: Settings) -> DataFrame:
    """(a, b, x, y): verified pairs of texts of one bucket but different labels x, y.

    ``mixed`` has (bucket, slot, node, n_words, label, brief, bag, text, blocks): the number of blocks of
    its bucket.  A pair is compared in its first common slot only, or in its pieces if it has none, and not where this task has linked
    its labels already; only links are rows.
    """

    def pairs(key: tuple, table: pa.Table) -> pa.Table:
        col = lambda c: table.column(c).to_numpy()
        node, words, label, block, slot = col("node"), col("n_words"), col("label"), col("block"), int(table.column("slot")[0].as_py())
        brief, bags = (np.frombuffer(b"".join(table.column(c).to_pylist()), kind).reshape(len(node), -1) for c, kind in (("brief", "<u4"), ("bag", "<u2")))
        first, second = key[1].as_py(), key[2].as_py()
        left, right = np.flatnonzero(block == first), np.flatnonzero(block == second)
        hashed, texts, parent = WordHash(), {}, {}
        found: list[tuple[int, int, int, int]] = []

        def top(x: int) -> int:
            while parent.setdefault(x, x) != x:
                parent[x] = x = parent[parent[x]]
            return x

        def text(i: int) -> Prepared:
            if i not in texts:
                texts[i] = Prepared(hashed.of(table.column("text")[i].as_py().split()).view(np.int64))
            return texts[i]

        def kept(p: np.ndarray, q: np.ndarray) -> np.ndarray:
            """The pairs of which this is the first common slot and whose words may be close enough."""
            fresh = ~(brief[p, :slot] == brief[q, :slot]).any(1)
            p, q = p[fresh], q[fresh]
            longer = np.maximum(words[p], words[q])
            least = longer - np.minimum(bags[p], bags[q]).sum(1, dtype=np.int64)
            near = (least <= (1 - settings.similarity) * longer + 1e-9) | (bags[p].sum(1) == 0) | (bags[q].sum(1) == 0)
            return np.stack([p[near], q[near]])

        step = max(1, (1 << 20) // max(1, len(right)))
        for lo in range(0, len(left), step):
            i = left[lo : lo + step]
            roots = {x: top(x) for x in np.unique(label[np.concatenate([i, right])]).tolist()}
            root = lambda at: np.array([roots[x] for x in label[at].tolist()], np.int64)
            ok = (root(i)[:, None] != root(right)) & (np.minimum(words[i][:, None], words[right]) >= settings.similarity * np.maximum(words[i][:, None], words[right]) - 1e-9)
            if first == second:
                ok &= node[i][:, None] < node[right]
            p, q = np.nonzero(ok)
            p, q = np.concatenate([kept(i[p[at : at + 65536]], right[q[at : at + 65536]]) for at in range(0, len(p), 65536)] or [np.zeros((2, 0), np.int64)], 1)
            todo = list(zip(p.tolist(), q.tolist()))
            for at in range(0, len(todo), 128):
                part = [(a, b) for a, b in todo[at : at + 128] if top(int(label[a])) != top(int(label[b]))]
                for (a, b), good in zip(part, within([(text(a), text(b)) for a, b in part], settings.similarity)):
                    if good:
                        parent[top(int(label[a]))] = top(int(label[b]))
                        found.append((*sorted((int(node[a]), int(node[b]))), int(label[a]), int(label[b])))
        return pa.table({c: pa.array([f[k] for f in found], pa.int64()) for k, c in enumerate("abxy")})

    own = F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int")
    dealt = mixed.withColumn("block", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    keys = [F.col("bucket"), F.least("block", "other").alias("first"), F.greatest("block", "other").alias("second")]
    return dealt.groupBy(*keys).applyInArrow(pairs, "a long, b long, x long, y long")


def classes_met(inside: DataFrame, labels: DataFrame) -> DataFrame:
    """(bucket, label, t): a row for each class of a bucket, however many texts it has there, with one of them; ``inside`` has (bucket, node, n_words)."""
    at = inside.join(labels, "node", "left").withColumn("label", F.coalesce("label", "node"))
    return at.groupBy("bucket", "label").agg(F.min(F.struct("node", "n_words")).alias("t"))


def class_pairs(met: DataFrame, similarity: float) -> DataFrame:
    """(a, b, x, y): a text of each class y of a bucket with one of its first class x, where the lengths fit; two pairs of texts for a pair of classes."""
    first = met.groupBy("bucket").agg(F.min(F.struct("label", "t")).alias("f"), F.max("label").alias("last")).where("f.label <> last").select("bucket", F.col("f.label").alias("x"), F.col("f.t").alias("u"))
    both = met.join(first, "bucket").where("label <> x").where(F.least("t.n_words", "u.n_words") >= similarity * F.greatest("t.n_words", "u.n_words") - 1e-9)
    both = both.select("x", F.col("label").alias("y"), F.struct(F.least("t.node", "u.node").alias("a"), F.greatest("t.node", "u.node").alias("b")).alias("e"))
    both = both.groupBy("x", "y").agg(F.min("e").alias("e0"), F.max("e").alias("e1"))
    return both.select("x", "y", F.explode(F.array_distinct(F.array("e0", "e1"))).alias("e")).select("e.a", "e.b", "x", "y")


#: Stands for a null id, after all others.
NO_ID = (1 << 63) - 1


def members(docs: DataFrame, settings: Settings, space: Workspace) -> tuple[DataFrame, DataFrame]:
    """(doc, node) of each row, ``node`` null for word-less texts, and (node, rep, label, n_links) of each node: the least id of its text and its class."""
    key = F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID))
    docs = docs.select("doc_id", "text")
    sk = space.keep(sketches(docs, settings).withColumn("rep", F.coalesce("doc", F.lit(NO_ID))))
    # equal texts: the least id stands for all of them
    first = space.keep(sk.where("node is not null").groupBy("node").agg(F.min("rep").alias("rep")))
    rows = sk.join(first, ["node", "rep"], "left_semi").select("node", "n_words", F.posexplode("sig").alias("slot", "s")).withColumn("slot", F.least("slot", F.lit(settings.slots)))
    rows = rows.select(F.xxhash64("slot", "s").alias("bucket"), "slot", "node", "n_words")
    several = rows.groupBy("bucket").agg(F.min("node").alias("a"), F.max("node").alias("z")).where("a <> z").select("bucket", "a")
    buckets = space.keep(rows.join(several, "bucket"))
    needed = buckets.select("node").distinct().join(first, "node")
    texts = docs.select(key.alias("rep"), F.xxhash64("text").alias("node"), "text")
    texts = space.keep(texts.join(needed, ["rep", "node"]).dropDuplicates(["rep", "node"]).select("node", "text"))
    near = F.least("n_words", "na") >= settings.similarity * F.greatest("n_words", "na") - 1e-9
    # first round: every text with the first of the texts that lead its buckets
    lengths = buckets.select(F.col("node").alias("a"), F.col("n_words").alias("na")).distinct()
    star = buckets.where("node <> a").select("node", "n_words", "a").distinct().join(lengths, "a").where(near)
    links = [space.keep(verify(star.groupBy(F.col("node").alias("b")).agg(F.min("a").alias("a")).select("a", "b"), texts, settings.similarity))]
    labels = components(links[0], space)
    inside = space.keep(buckets.select("bucket", "slot", "node", "n_words").distinct())
    space.drop(buckets)

    def labelled_members(labels: DataFrame) -> DataFrame:
        """Members of buckets in which texts of several classes are left, with ``blocks`` of the bucket."""
        at = inside.join(labels, "node", "left").withColumn("label", F.coalesce("label", "node"))
        blocks = F.ceil(F.count(F.lit(1)) / settings.block).cast("int").alias("blocks")
        mixed = at.groupBy("bucket").agg(F.min("label").alias("lead"), F.max("label").alias("l1"), blocks).where("lead <> l1").select("bucket", "lead", "blocks")
        return at.join(mixed, "bucket")

    def merged(labels: DataFrame, found: DataFrame) -> DataFrame:
        """Labels after the links (a, b) of the classes x and y."""
        links.append(space.keep(found))
        moved = components(links[-1].select(F.col("x").alias("a"), F.col("y").alias("b")), space).select(F.col("node").alias("label"), F.col("label").alias("to"))
        fresh = moved.select(F.col("label").alias("node"), F.col("to").alias("label")).join(labels, "node", "left_anti")
        return space.keep(labels.join(moved, "label", "left").select("node", F.coalesce("to", "label").alias("label")).unionByName(fresh))

    # next: in each bucket one text of every class with one of the first class
    for _ in range(settings.class_rounds):
        met = space.keep(classes_met(inside, labels))
        pairs = space.keep(class_pairs(met, settings.similarity))
        space.drop(met)
        labels = merged(labels, verify(pairs.select("a", "b"), texts, settings.similarity).join(pairs, ["a", "b"]))
    # last: all pairs of texts of different classes; a text meets its buckets as one row, so the joins give a row a text
    left = labelled_members(labels).groupBy("node", "n_words", "label").agg(F.collect_list(F.struct("bucket", "slot", "blocks")).alias("at"))
    left = space.keep(left)
    brief = first.join(left.select("node"), "node").join(sk.select("node", "rep", "brief", "bag"), ["node", "rep"]).dropDuplicates(["node"]).select("node", "brief", "bag")
    space.drop(inside)
    mixed = left.join(brief.join(texts, "node"), "node").select("node", "n_words", "label", "brief", "bag", "text", F.explode("at").alias("at"))
    labels = merged(labels, linked(mixed.select("at.*", "node", "n_words", "label", "brief", "bag", "text"), settings))
    degree = reduce(DataFrame.union, [x.select("a", "b") for x in links]).select(F.explode(F.array("a", "b")).alias("node")).groupBy("node").agg(F.count(F.lit(1)).alias("n_links"))
    named = first.join(labels, "node", "left").withColumn("label", F.coalesce("label", "node"))
    return sk.select("doc", "node"), named.join(degree, "node", "left").select("node", "rep", "label", F.coalesce("n_links", F.lit(0).cast("long")).alias("n_links"))


def classes(docs: DataFrame, settings: Settings | None = None) -> DataFrame:
    """(doc_id, class_id, n_links): each row's class and the number of verified links of its text.

    Not every link of a class is looked for: two texts already in one class are not compared.  Classes
    whose least texts stand under one id get the same id.
    """
    with Workspace(docs.sparkSession) as space:
        rows, nodes = members(docs, settings or Settings(), space)
        ids = nodes.groupBy("label").agg(F.min("rep").alias("class_id"))
        member = nodes.join(ids, "label").select("node", F.nullif("class_id", F.lit(NO_ID)).alias("class_id"), "n_links")
        out = rows.join(member, "node", "left")
        class_id = F.when(F.col("n_links").isNull(), F.col("doc")).otherwise(F.col("class_id"))
        return cut(out.select(F.col("doc").alias("doc_id"), class_id.alias("class_id"), F.coalesce("n_links", F.lit(0).cast("long")).alias("n_links")))


def keep_first(docs: DataFrame, settings: Settings | None = None) -> DataFrame:
    """The rows of ``docs`` that stay: of each class one row of its least id; null and word-less texts all stay.

    Classes are told by their texts, so several under one id, or under none, each keep a row.
    """
    with Workspace(docs.sparkSession) as space:
        _, nodes = members(docs, settings or Settings(), space)
        stay = nodes.groupBy("label").agg(F.min(F.struct("rep", "node")).alias("t")).select("t.rep", "t.node")
        node, rep = unused(docs, "node"), unused(docs, "rep")
        stay = stay.toDF(rep, node)
        has_words = F.coalesce("text", F.lit("")).rlike(r"\S")
        named = docs.withColumns({node: F.when(has_words, F.xxhash64("text")), rep: F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID))})
        alone, rest = named.where(F.col(node).isNull()), named.where(F.col(node).isNotNull())
        first = rest.join(stay, [node, rep], "left_semi").dropDuplicates([node])
        return cut(first.unionByName(alone).select(*[F.col(f"`{c}`") for c in docs.columns]))
