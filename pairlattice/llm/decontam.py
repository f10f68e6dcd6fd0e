"""Benchmark decontamination: random-walk embedding, bit-sampling LSH, exact edit verification.

A document is contaminated by an item when some stretch of its words is within (1 - similarity) of
the item's words in edit distance.  Words are lower-cased.

1. An item cut into one more piece than the edits it may have keeps one piece whole (pigeonhole), so
   the places where a piece stands give all item-sized windows that can match: nothing is lost here.
2. The CGK embedding walks through window and item with shared random bits, so a small edit distance
   becomes a small Hamming distance; ``walks`` x ``tables`` samples of ``bits`` positions each, all
   before the walks end, are compared, as many as the target recall needs at the agreement counted on.
3. What collides is verified exactly by the edit distance of the item to the best stretch around the
   window.

Defined results: null or word-less texts and items match nothing; an item of fewer than five words
must stand exactly; equal items are reported each; repeated rows each get a row; whole texts of any
length are processed; further columns are ignored; an empty table gives no rows.  Items are handed to
the tasks in blocks of bounded size; each block is one more pass over the documents.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairlattice.llm.common import slices, tidy

ODD = np.uint64(0x9E3779B97F4A7C15)
MIX = np.uint64(0xD6E8FEB86659FD93)
BITMAP_BITS = 18


@dataclass(frozen=True)
class Settings:
    similarity: float = 0.8
    target_recall: float = 0.99
    #: Share of sampled positions on which a match is counted on to agree; windows that share no more than chance agree on a few hundredths.
    agreement: float = 0.5
    bits: int = 3
    walks: int = 8
    seed: int = 3
    block_bytes: int = 16 << 20

    @property
    def tables(self) -> int:
        """Samples of each walk, so that all of them together reach the target recall."""
        return math.ceil(math.log(1 - self.target_recall) / math.log(1 - self.agreement**self.bits) / self.walks)


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * MIX
    return x ^ (x >> np.uint64(29))


class Vocabulary(dict):
    """Hash of a word of the items; 0 for any other."""

    def __missing__(self, word: str) -> int:
        return 0


class Items:
    """A block of items: pieces to look for, embeddings, sampled positions."""

    def __init__(self, items: list[tuple[int, str]], settings: Settings):
        self.settings = s = settings
        self.ids = [i for i, _ in items]
        words = [t.lower().split() for _, t in items]
        self.vocab = Vocabulary((w, xxhash.xxh3_64_intdigest(w.encode("utf-8", "surrogatepass")) >> 1 | 1) for ws in words for w in ws)
        self.words = [np.fromiter((self.vocab[w] for w in ws), np.uint64, len(ws)) for ws in words]
        self.size = np.array([len(w) for w in self.words], np.int64)
        self.edits = ((1 - s.similarity) * self.size + 1e-9).astype(np.int64)
        self.longest = int(self.size.max(initial=0))
        keys: dict[int, list[tuple[int, int, int]]] = {}
        for k, (w, n, e) in enumerate(zip(self.words, self.size, self.edits)):
            length = int(n // (e + 1))
            for p in range(int(e) + 1):
                at = int(p * n // (e + 1))
                keys.setdefault(length, []).append((int(grams(w[at : at + length], length)[0]), k, at))
        self.pieces = {}
        for length, found in keys.items():
            found.sort()
            key = np.array([f[0] for f in found], np.uint64)
            bitmap = np.zeros(1 << BITMAP_BITS, bool)
            bitmap[(key >> np.uint64(64 - BITMAP_BITS)).astype(np.int64)] = True
            self.pieces[length] = key, np.array([f[1] for f in found]), np.array([f[2] for f in found]), bitmap
        rng = np.random.default_rng(s.seed)
        draw = lambda *shape: rng.integers(0, 2**63, shape, np.int64).astype(np.uint64) * np.uint64(2) | np.uint64(1)
        self.steps = draw(3 * self.longest, s.walks)
        share = rng.random((s.walks, s.tables, s.bits))
        # a walk takes two steps a word on average; later positions would be padding on both sides, which agrees always
        self.places = (share[None] * 1.7 * self.size[:, None, None, None]).astype(np.int64)
        flat = np.concatenate([*self.words, np.zeros(1, np.uint64)])
        start = np.concatenate([[0], np.cumsum(self.size)[:-1]]) if len(self.size) else np.zeros(0, np.int64)
        self.samples = self.sample(flat, start, np.arange(len(self.size))) if len(self.size) else None

    def sample(self, flat: np.ndarray, start: np.ndarray, item: np.ndarray) -> np.ndarray:
        """Sampled symbols (windows, walks, tables, bits) of the embedded windows flat[start : start + size of item]."""
        n = self.size[item][:, None]
        at = np.zeros((len(start), self.settings.walks), np.int64)
        out = np.zeros((len(start), self.settings.walks, 3 * int(n.max())), np.uint64)
        for t in range(out.shape[2]):
            inside = at < n
            where = start[:, None] + at
            symbol = np.where(inside & (where >= 0) & (where < len(flat)), flat[np.clip(where, 0, len(flat) - 1)], np.uint64(0)) + inside.astype(np.uint64)
            out[:, :, t] = symbol
            at += (mix(symbol * self.steps[t]) >> np.uint64(63)).astype(np.int64) & inside
        place = self.places[item]
        rows, walk = np.arange(len(start))[:, None, None, None], np.arange(self.settings.walks)[None, :, None, None]
        return out[rows, walk, place]

    def windows(self, flat: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Distinct (start, item) of the windows that hold a piece of an item at its place."""
        starts, items = [], []
        for length, (key, item, offset, bitmap) in self.pieces.items():
            if length > len(flat):
                continue
            h = grams(flat, length)
            gap = np.concatenate([[0], np.cumsum(flat == 0)])
            pos = np.nonzero(bitmap[(h >> np.uint64(64 - BITMAP_BITS)).astype(np.int64)] & (gap[length:] == gap[: len(h)]))[0]
            lo, hi = np.searchsorted(key, h[pos], "left"), np.searchsorted(key, h[pos], "right")
            n = hi - lo
            pos, lo, n = pos[n > 0], lo[n > 0], n[n > 0]
            entry = np.repeat(lo - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum()) if len(n) else np.zeros(0, np.int64)
            starts.append(np.repeat(pos, n) - offset[entry])
            items.append(item[entry])
        if not starts:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        both = np.unique(np.stack([np.concatenate(starts), np.concatenate(items)], 1), axis=0)
        return both[:, 0], both[:, 1]

    def collide(self, flat: np.ndarray, start: np.ndarray, item: np.ndarray) -> np.ndarray:
        ok = np.zeros(len(start), bool)
        step = max(1, (1 << 22) // (3 * self.longest * self.settings.walks * 8))
        for lo in range(0, len(start), step):
            s = slice(lo, lo + step)
            same = self.sample(flat, start[s], item[s]) == self.samples[item[s]]
            ok[s] = same.all(3).any((1, 2))
        return ok

    def distances(self, flat: np.ndarray, start: np.ndarray, item: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        """Exact edit distance of each item to its best stretch around the window, inside flat[low : high)."""
        out = np.zeros(len(start), np.int64)
        wide = self.longest + 4 * int(self.edits.max(initial=0)) + 1
        step = max(1, (1 << 18) // wide)
        for lo in range(0, len(start), step):
            s = slice(lo, lo + step)
            it, n, slack = item[s], self.size[item[s]], 2 * self.edits[item[s]]
            first = start[s] - slack
            at = first[:, None] + np.arange(wide)
            inside = (at >= low[s][:, None]) & (at < high[s][:, None]) & (at < (start[s] + n + slack)[:, None])
            text = np.where(inside, flat[np.clip(at, 0, len(flat) - 1)], np.uint64(0))
            row = np.zeros((len(it), wide + 1), np.int32)
            ramp = np.arange(wide + 1, dtype=np.int32)
            for i in range(1, int(n.max()) + 1):
                word = np.array([self.words[k][i - 1] if i <= len(self.words[k]) else 0 for k in it], np.uint64)
                cost = ((text != word[:, None]) | (text == 0)).astype(np.int32)
                now = np.empty_like(row)
                now[:, 0] = i
                np.minimum(row[:, :-1] + cost, row[:, 1:] + 1, out=now[:, 1:])
                now = np.minimum.accumulate(now - ramp, 1) + ramp
                done = i > n
                now[done] = row[done]
                row = now
            out[s] = row.min(1)
        return out

    def search(self, texts: list[str | None]) -> list[list[tuple[int, int, int]]]:
        """(item id, first word of the window, distance) of each item found in each text, the best window of each."""
        get = self.vocab.__getitem__
        words = [np.fromiter(map(get, w), np.uint64, len(w)) for w in (t.lower().split() if t else [] for t in texts)]
        gap = np.zeros(1, np.uint64)
        flat = np.concatenate([x for w in words for x in (w, gap)]) if words else gap
        ends = np.cumsum([len(w) + 1 for w in words])
        begins = ends - [len(w) + 1 for w in words]
        out: list[list[tuple[int, int, int]]] = [[] for _ in texts]
        start, item = self.windows(flat)
        if not len(start):
            return out
        # a window belongs to the text of its piece; its start may lie up to one item before the text
        middle = np.clip(start + self.size[item] // 2, 0, len(flat) - 1)
        doc = np.searchsorted(ends, np.maximum(start, 0), "right")
        other = np.searchsorted(ends, middle, "right")
        both = other != doc
        start, item, doc = np.concatenate([start, start[both]]), np.concatenate([item, item[both]]), np.concatenate([doc, other[both]])
        keep = self.collide(flat, start, item)
        start, item, doc = start[keep], item[keep], doc[keep]
        far = self.distances(flat, start, item, begins[doc], ends[doc] - 1)
        best: dict[tuple[int, int], tuple[int, int]] = {}
        for d, k, s, e in zip(doc.tolist(), item.tolist(), start.tolist(), far.tolist()):
            if e <= self.edits[k]:
                x = (e, max(0, s - int(begins[d])))
                if (d, k) not in best or x < best[d, k]:
                    best[d, k] = x
        for (d, k), (e, s) in sorted(best.items()):
            out[d].append((self.ids[k], s, e))
        return out


def grams(words: np.ndarray, length: int) -> np.ndarray:
    h = np.zeros(len(words) - length + 1, np.uint64)
    for j in range(length):
        h = h * ODD + words[j : j + len(h)]
    return mix(h)


HITS = "array<struct<item_id:bigint,start_word:int,distance:int>>"
HITS_ARROW = pa.list_(pa.struct([("item_id", pa.int64()), ("start_word", pa.int32()), ("distance", pa.int32())]))


def blocks(benchmark: DataFrame, settings: Settings) -> Iterator[list[tuple[int, str]]]:
    block, size = [], 0
    for r in benchmark.select("item_id", "text").where("text is not null").orderBy("item_id", "text").toLocalIterator():
        if not r[1].split():
            continue
        block.append((r[0], r[1]))
        size += len(r[1])
        if size > settings.block_bytes:
            yield block
            block, size = [], 0
    if block:
        yield block


def contamination(docs: DataFrame, benchmark: DataFrame, settings: Settings | None = None) -> DataFrame:
    """(doc_id, contaminated, n_items, hits) of each row; narrow, one pass over the texts for each block of items."""
    settings = settings or Settings()
    kind = dict(docs.dtypes)["doc_id"]
    now = docs.select("doc_id", "text", F.array().cast(HITS).alias("hits"))
    for block in blocks(benchmark, settings):

        def run(batches: Iterator[pa.RecordBatch], block=block) -> Iterator[pa.RecordBatch]:
            items = Items(block, settings)
            for batch in batches:
                texts, before = batch.column(1).to_pylist(), batch.column(2).to_pylist()
                for lo, hi in slices(texts):
                    found = items.search(texts[lo:hi])
                    hits = [b + [{"item_id": i, "start_word": s, "distance": e} for i, s, e in f] for b, f in zip(before[lo:hi], found)]
                    yield pa.RecordBatch.from_arrays([*(batch.column(k).slice(lo, hi - lo) for k in range(2)), pa.array(hits, HITS_ARROW)], names=["doc_id", "text", "hits"])

        now = now.mapInArrow(tidy(run), f"doc_id {kind}, text string, hits {HITS}")
    return now.select("doc_id", (F.size("hits") > 0).alias("contaminated"), F.size("hits").cast("long").alias("n_items"), "hits")


def clean(docs: DataFrame, benchmark: DataFrame, settings: Settings | None = None) -> DataFrame:
    """The rows of ``docs`` that no item contaminates, with all their columns; rows with equal ids are judged one by one by their text."""
    settings = settings or Settings()
    kept = docs
    for block in blocks(benchmark, settings):

        def run(batches: Iterator[pa.RecordBatch], block=block) -> Iterator[pa.RecordBatch]:
            items = Items(block, settings)
            for batch in batches:
                texts = batch.column(batch.schema.get_field_index("text")).to_pylist()
                for lo, hi in slices(texts):
                    yield batch.slice(lo, hi - lo).filter(pa.array([not x for x in items.search(texts[lo:hi])]))

        kept = kept.mapInArrow(tidy(run), kept.schema)
    return kept if kept is not docs else docs.select("*")
