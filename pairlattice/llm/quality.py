"""Quality classifier: supervised subword embeddings.

Every word, its character n-grams and every pair of neighbouring words are hashed to rows of an
embedding table (a pair of equal words to one row whatever the word, so that runs of a repeated word
are told by a feature all of them share); a document is the average of its rows; a softmax layer
gives the label.  All weights are fitted by stochastic gradient
descent in numpy, in one task, on at most ``most_rows`` labelled rows.

Because the average and the last layer are linear, a word adds the same amount to the logit wherever
it stands; scoring keeps one number and one hash per word.

Defined results: a null or word-less text gets the score of the bias alone; several labels of one
document count as separate rows; null labels and those of a null id are not learned; without labels of both kinds every
score is the share of ones (0.5 if there are none); repeated rows each get a row; further columns
are ignored.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairlattice.llm.common import tidy

CACHE_WORDS = 200_000


@dataclass(frozen=True)
class Settings:
    buckets: int = 1 << 16
    dim: int = 8
    grams: tuple[int, ...] = (2, 3, 4)
    epochs: int = 4
    batch: int = 32
    rate: float = 0.2
    seed: int = 11
    #: Most labelled rows the model is fitted on, those of the least hashed ids.
    most_rows: int = 3000
    threshold: float = 0.7
    #: How often a pair of neighbouring words counts, beside about ten n-grams of a word.
    pair_weight: float = 4.0


@dataclass
class Model:
    table: np.ndarray
    weight: np.ndarray
    bias: float
    settings: Settings


class WordRows:
    """One row of numbers per word, computed for words of one length together; bounded memory."""

    def __init__(self, width: int, compute: Callable[[np.ndarray], np.ndarray]):
        self.width, self.compute = width, compute
        self.clear()

    def clear(self) -> None:
        self.index: dict[str, int] = {}
        self.rows = np.zeros((CACHE_WORDS, self.width))

    def learn(self, words: set[str]) -> None:
        new = [w for w in words if w not in self.index]
        if len(self.index) + len(new) > len(self.rows):
            self.clear()
            new = list(words)
            if len(new) > len(self.rows):
                self.rows = np.zeros((len(new), self.width))
        by_length: dict[int, list[str]] = {}
        for w in new:
            by_length.setdefault(len(w), []).append(w)
        for size, same in by_length.items():
            step = max(1, min(4096, (1 << 18) // (size + 2)))
            for k in range(0, len(same), step):
                part = same[k : k + step]
                codes = np.frombuffer("".join(part).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64).reshape(len(part), size)
                base = len(self.index)
                self.rows[base : base + len(part)] = self.compute(codes)
                self.index.update((w, base + i) for i, w in enumerate(part))

    def of(self, words: list[str]) -> np.ndarray:
        return self.rows[np.fromiter(map(self.index.__getitem__, words), np.int64, len(words))]


def features(codes: np.ndarray, settings: Settings) -> np.ndarray:
    """Hashed ids of the word and of its n-grams between word marks; a word of each row."""
    n, size = codes.shape
    edge = np.full((n, 1), 0x10FFFF + 1, np.uint64)
    c = np.concatenate([edge, codes + np.uint64(1), edge], 1)
    prime, out = np.uint64(0x100000001B3), []
    mix = lambda h, salt: ((h ^ np.uint64(salt)) * np.uint64(0xC2B2AE3D27D4EB4F)) >> np.uint64(32)
    h = np.zeros((n, size + 2), np.uint64)
    whole = np.zeros(n, np.uint64)
    for j in range(size + 2):
        whole = whole * prime + c[:, j]
    out.append(mix(whole, 1)[:, None])
    for length in range(1, max(settings.grams) + 1):
        if length > size + 2:
            break
        h = h[:, : size + 3 - length] * prime + c[:, length - 1 :]
        if length in settings.grams:
            out.append(mix(h, 1 + length))
    return (np.concatenate(out, 1) % np.uint64(settings.buckets)).astype(np.int64)


def pair_ids(words: np.ndarray, settings: Settings) -> np.ndarray:
    """Rows of the pairs of neighbours in a sequence of word ids."""
    a, b = words[:-1].astype(np.uint64), words[1:].astype(np.uint64)
    mixed = ((a * np.uint64(0x9E3779B97F4A7C15) + b) * np.uint64(0xC2B2AE3D27D4EB4F)) >> np.uint64(32)
    return np.where(a == b, 0, mixed % np.uint64(settings.buckets)).astype(np.int64)


def bag(text: str | None, settings: Settings) -> tuple[np.ndarray, np.ndarray]:
    """Distinct feature ids of a text and their shares."""
    order = text.split() if text else []
    words = Counter(order)
    by_length: dict[int, list[str]] = {}
    for w in words:
        by_length.setdefault(len(w), []).append(w)
    total, whole = np.zeros(settings.buckets), {}
    for size, same in by_length.items():
        codes = np.frombuffer("".join(same).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64).reshape(len(same), size)
        ids = features(codes, settings)
        whole.update(zip(same, ids[:, 0].tolist()))
        total += np.bincount(ids.ravel(), np.repeat(np.array([words[w] for w in same], float), ids.shape[1]), settings.buckets)
    if len(order) > 1:
        total += settings.pair_weight * np.bincount(pair_ids(np.array([whole[w] for w in order]), settings), minlength=settings.buckets)
    at = np.nonzero(total)[0].astype(np.int32)
    return at, (total[at] / max(total.sum(), 1)).astype(np.float32)


def train(texts: list[str | None], labels: list[int], settings: Settings) -> Model:
    """Gradient descent with per-weight step sizes; the order of the rows is fixed by the seed."""
    y = np.array(labels, float)
    rng = np.random.default_rng(settings.seed)
    table = rng.normal(0, 0.1, (settings.buckets, settings.dim))
    weight = rng.normal(0, 0.1, settings.dim)
    share = y.mean() if len(y) else 0.5
    if not len(y) or not 0 < share < 1:
        return Model(table, weight * 0, float(np.log((share + 1e-6) / (1 - share + 1e-6))) if len(y) else 0.0, settings)
    bias, seen_t, seen_w, seen_b = float(np.log(share / (1 - share))), np.full(table.shape, 1e-8), np.full(weight.shape, 1e-8), 1e-8
    bags = [bag(t, settings) for t in texts]
    for epoch in range(settings.epochs):
        rate = settings.rate * (1 - epoch / settings.epochs)
        order = rng.permutation(len(bags))
        for lo in range(0, len(order), settings.batch):
            part = order[lo : lo + settings.batch]
            ids = np.concatenate([bags[i][0] for i in part])
            share_of = np.concatenate([bags[i][1] for i in part])
            doc = np.repeat(np.arange(len(part)), [len(bags[i][0]) for i in part])
            mean = np.stack([np.bincount(doc, share_of * table[ids, k], len(part)) for k in range(settings.dim)], 1)
            p = 1 / (1 + np.exp(-np.clip(mean @ weight + bias, -30, 30)))
            g = (p - y[part]) / len(part)
            gw, gb = mean.T @ g, g.sum()
            gt = np.bincount(ids, share_of * g[doc], settings.buckets)[:, None] * weight
            seen_t += gt * gt
            seen_w += gw * gw
            seen_b += gb * gb
            table -= rate * gt / np.sqrt(seen_t)
            weight -= rate * gw / np.sqrt(seen_w)
            bias -= rate * gb / np.sqrt(seen_b)
    return Model(table, weight, float(bias), settings)


def fit(docs: DataFrame, labels: DataFrame, settings: Settings | None = None) -> Model:
    """Fit on (doc_id, text) and (doc_id, quality).

    The sample is fixed by the hash of the id; its texts meet in one task, whose memory is bounded by
    ``most_rows`` bags of features; the table is scanned and joined in parallel before.  The driver
    receives the weights only.
    """
    settings = settings or Settings()
    rows = labels.where("quality is not null and doc_id is not null").select("doc_id", F.col("quality").cast("int").alias("quality"))
    rows = rows.join(docs.select("doc_id"), "doc_id", "left_semi")
    chosen = F.broadcast(rows.orderBy(F.xxhash64("doc_id"), "doc_id", "quality").limit(settings.most_rows))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = sorted((r for b in batches for r in zip(*(b.column(i).to_pylist() for i in range(3)))), key=lambda r: (r[0], r[2], r[1] or ""))
        m = train([r[1] for r in got], [int(r[2] == 1) for r in got], settings)
        yield pa.RecordBatch.from_arrays([pa.array([m.table.astype(np.float32).tobytes()], pa.binary()), pa.array([m.weight.tobytes()], pa.binary()), pa.array([m.bias], pa.float64())], names=["table", "weight", "bias"])

    got = docs.select("doc_id", "text").join(chosen, "doc_id").repartition(1).mapInArrow(tidy(run), "table binary, weight binary, bias double").first()
    if got is None:
        return train([], [], settings)
    return Model(np.frombuffer(got[0], np.float32).reshape(settings.buckets, settings.dim).astype(float), np.frombuffer(got[1]), got[2], settings)


class Scorer:
    """Scores of texts; keeps a bounded number of words."""

    def __init__(self, model: Model):
        self.bias, self.settings = model.bias, model.settings
        logits = self.logits = model.table @ model.weight

        def compute(codes: np.ndarray) -> np.ndarray:
            ids = features(codes, model.settings)
            return np.stack([logits[ids].sum(1), np.full(len(ids), float(ids.shape[1])), ids[:, 0].astype(float)], 1)

        self.known = WordRows(3, compute)

    def scores(self, texts: list[str | None]) -> np.ndarray:
        out: list[float] = []
        part: list[list[str]] = []
        size = 0
        for t in texts:  # words of a part only are held, they take many times the memory of their texts
            w = t.split() if t else []
            if part and size + len(w) > CACHE_WORDS:
                out += self.of(part)
                part, size = [], 0
            part.append(w)
            size += len(w)
        return np.array(out + self.of(part))

    def of(self, texts: list[list[str]]) -> list[float]:
        """Scores of split texts, whose words are all known at once."""
        out, weight = [], self.settings.pair_weight
        self.known.learn(set().union(*texts))
        for w in texts:
            z = self.bias
            if w:
                rows = self.known.of(w)
                pairs = self.logits[pair_ids(rows[:, 2], self.settings)]
                z += (rows[:, 0].sum() + weight * pairs.sum()) / (rows[:, 1].sum() + weight * len(pairs))
            out.append(float(1 / (1 + np.exp(-min(30.0, max(-30.0, z))))))
        return out


def score(docs: DataFrame, model: Model) -> DataFrame:
    """(doc_id, score, predicted) of each whole text; narrow."""
    kind = dict(docs.dtypes)["doc_id"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        judge = Scorer(model)
        for batch in batches:
            p = judge.scores(batch.column(1).to_pylist())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(p), pa.array((p >= model.settings.threshold).astype(np.int32))], names=["doc_id", "score", "predicted"])

    return docs.select("doc_id", "text").mapInArrow(tidy(run), f"doc_id {kind}, score double, predicted int")


def accepted(docs: DataFrame, model: Model) -> DataFrame:
    """The rows of ``docs`` whose text reaches the threshold, with all their columns; narrow."""
    names = docs.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        judge = Scorer(model)
        for batch in batches:
            p = judge.scores(batch.column(names.index("text")).to_pylist())
            yield batch.filter(pa.array(p >= model.settings.threshold))

    return docs.mapInArrow(tidy(run), docs.schema)
