"""Language identification: unigram piece probabilities per language, summed over all segmentations.

A fixed public piece vocabulary; per language, piece counts of the training texts give smoothed
probabilities.  The score of a word is the log of the sum over all its segmentations (forward
algorithm); words are independent, so a text's score is the sum over its words.

Defined results: null text, or text without a letter, is ``und`` with score 0; a null language is not
learned; no training rows at all make every text ``und``; ties go to the first language by name;
repeated rows each get a row; long texts are scored whole; further columns are ignored.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairlattice.llm.common import tidy

from pairlattice.llm.sentencepiece import SPACE, Encoder, PieceTable

UNKNOWN = "und"
LETTERS = re.compile(r"[^\W\d_]+")
CACHE_WORDS = 200_000


@dataclass
class LanguageModel:
    """Natural-log probabilities, one row per language; size = languages x vocabulary."""

    langs: list[str]
    logp: np.ndarray
    unknown: np.ndarray
    prior: np.ndarray

    @cached_property
    def scaled(self) -> np.ndarray:
        """Probabilities times e to ``SCALE``, a row for each piece."""
        return np.ascontiguousarray(np.exp(self.logp.T + SCALE))


def fold(text: str) -> str:
    return text.lower()


def piece_counts(docs: DataFrame, pieces: PieceTable) -> DataFrame:
    """(lang, piece, n) over the whole texts; each task combines its own counts before the shuffle.

    Piece -1 counts documents.  Words are segmented once each by the base scores of the vocabulary.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[str, np.ndarray] = {}
        enc = Encoder(pieces)
        n = len(pieces.pieces)

        def add(lang: str, words: Counter) -> None:
            keys = list(words)
            enc.learn(enc.spaced, set(keys), True)
            ids = [np.frombuffer(enc.spaced[w], "<i4") for w in keys]
            times = np.repeat(np.fromiter(words.values(), np.float64, len(words)), [len(x) for x in ids])
            total[lang][:n] += np.bincount(np.concatenate(ids), times, n)

        for batch in batches:
            seen: dict[str, Counter] = {}
            for text, lang in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                c = seen.setdefault(lang, Counter())
                total.setdefault(lang, np.zeros(n + 1))[n] += 1
                c.update(LETTERS.findall(fold(text)))
                if len(c) > 50_000:
                    add(lang, c)
                    c.clear()
            for lang, c in seen.items():
                if c:
                    add(lang, c)
        for lang, v in total.items():
            at = np.nonzero(v)[0]
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at)), pa.array(np.where(at == n, -1, at), pa.int32()), pa.array(v[at].astype(np.int64))], names=["lang", "piece", "n"])

    rows = docs.select("text", "lang").where(F.col("text").isNotNull() & F.col("lang").isNotNull())
    return rows.mapInArrow(tidy(run), "lang string, piece int, n long").groupBy("lang", "piece").agg(F.sum("n").alias("n"))


def fit(docs: DataFrame, pieces: PieceTable, smoothing: float = 0.5, most_langs: int = 1000) -> LanguageModel:
    """Learn from (text, lang); the driver receives at most languages x vocabulary counts."""
    got = piece_counts(docs, pieces).toPandas()
    langs = sorted(set(got["lang"]))
    if len(langs) > most_langs:
        raise ValueError(f"{len(langs)} languages; the model is kept small by at most {most_langs}")
    n = len(pieces.pieces)
    counts, prior = np.zeros((len(langs), n)), np.zeros(len(langs))
    at = {x: i for i, x in enumerate(langs)}
    row, piece = got["lang"].map(at).to_numpy(int), got["piece"].to_numpy(int)
    counts[row[piece >= 0], piece[piece >= 0]] = got["n"].to_numpy()[piece >= 0]
    prior[row[piece < 0]] = got["n"].to_numpy()[piece < 0]
    usable = np.zeros(n, bool)
    usable[pieces.key_ids] = True
    usable[pieces.byte_ids] = True
    mass = counts + smoothing * usable
    logp = np.where(usable, np.log(np.maximum(mass, 1e-300) / mass.sum(1, keepdims=True)), -np.inf) if len(langs) else counts
    unknown = np.array([np.log(smoothing / m.sum()) for m in mass]) - 7
    return LanguageModel(langs, logp, unknown, np.log(prior / max(prior.sum(), 1)) if len(langs) else prior)


#: Words up to this length are summed as scaled probabilities, which stay far from the ends of doubles; longer ones as logs.
SHORT, SCALE = 24, 8.0


def forward(pieces: PieceTable, model: LanguageModel, codes: np.ndarray) -> np.ndarray:
    """Log of the summed probability of all segmentations: words of one length x languages."""
    n, size = codes.shape
    found = pieces.spans(codes)
    if size <= SHORT and model.unknown.min(initial=0) > -40:
        return np.log(summed(model, found, n, size)) - SCALE * size
    alpha = np.full((size + 1, n, len(model.langs)), -np.inf)
    alpha[0] = 0
    for end in range(1, size + 1):
        cand = []
        for k in range(1, min(len(found), end) + 1):
            ids = found[k - 1][:, end - k]
            if k == 1 or (ids >= 0).any():
                p = np.where(ids[:, None] >= 0, model.logp[:, ids].T, model.unknown if k == 1 else -np.inf)
                cand.append(alpha[end - k] + p)
        c = np.stack(cand)
        top = c.max(0)
        alpha[end] = top + np.log(np.exp(c - top).sum(0))
    return alpha[size]


def summed(model: LanguageModel, found: list[np.ndarray], n: int, size: int) -> np.ndarray:
    """Summed probabilities, each character of a word times e to ``SCALE``; only pieces that occur are looked at."""
    alpha = np.ones((size + 1, n, len(model.langs)))
    for end in range(1, size + 1):
        ids = found[0][:, end - 1]
        total = alpha[end - 1] * np.where(ids[:, None] >= 0, model.scaled.take(ids, 0), np.exp(model.unknown + SCALE))
        for k in range(2, min(len(found), end) + 1):
            ids = found[k - 1][:, end - k]
            at = np.flatnonzero(ids >= 0)
            if len(at):
                total[at] += alpha[end - k].take(at, 0) * model.scaled.take(ids[at], 0) * np.exp(SCALE * (k - 1))
        alpha[end] = total
    return alpha[size]


class WordScores:
    """Scores of words seen, kept in one growing matrix of bounded size."""

    def __init__(self, pieces: PieceTable, model: LanguageModel):
        self.pieces, self.model = pieces, model
        self.clear()

    def clear(self) -> None:
        self.index: dict[str, int] = {}
        self.rows = np.zeros((CACHE_WORDS * 2, len(self.model.langs)))

    def learn(self, words: set[str]) -> None:
        new = [w for w in words if w not in self.index]
        if len(self.index) + len(new) > CACHE_WORDS:
            self.clear()
            new = list(words)
        if len(new) > len(self.rows):
            self.rows = np.zeros((len(new), self.rows.shape[1]))
        by_length: dict[int, list[str]] = {}
        for w in new:
            by_length.setdefault(len(w), []).append(w)
        for size, same in by_length.items():
            step = max(1, min(2048, (1 << 17) // (size + 1)))
            for k in range(0, len(same), step):
                part = same[k : k + step]
                codes = np.frombuffer("".join(part).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64).reshape(len(part), size)
                codes = np.concatenate([np.full((len(part), 1), ord(SPACE), np.int64), codes], 1)
                base = len(self.index)
                self.rows[base : base + len(part)] = forward(self.pieces, self.model, codes)
                self.index.update((w, base + i) for i, w in enumerate(part))


def predict(docs: DataFrame, pieces: PieceTable, model: LanguageModel) -> DataFrame:
    """(doc_id, lang_pred, score, log_prob) of each text; ``score`` is the posterior of the predicted language."""
    kind = dict(docs.dtypes)["doc_id"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = WordScores(pieces, model)
        for batch in batches:
            langs, scores, logs = [], [], []
            texts = batch.column(1).to_pylist()
            step = 1000
            for lo in range(0, len(texts), step):
                words = [LETTERS.findall(fold(t)) if t and model.langs else [] for t in texts[lo : lo + step]]
                groups, size = [[]], 0
                for w in words:  # groups of a bounded number of words, so the cache holds each group's
                    if size and size + len(w) > CACHE_WORDS:
                        groups.append([])
                        size = 0
                    groups[-1].append(w)
                    size += len(w)
                for group in groups:
                    known.learn(set().union(*group))
                    for w in group:
                        if not w:
                            langs.append(UNKNOWN), scores.append(0.0), logs.append(None)
                            continue
                        x = known.rows[np.fromiter(map(known.index.__getitem__, w), np.int64, len(w))].sum(0) + model.prior
                        k = int(x.argmax())
                        langs.append(model.langs[k]), scores.append(float(1 / np.exp(x - x[k]).sum())), logs.append(float(x[k]))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(langs, pa.string()), pa.array(scores, pa.float64()), pa.array(logs, pa.float64())], names=["doc_id", "lang_pred", "score", "log_prob"])

    return docs.select("doc_id", "text").mapInArrow(tidy(run), f"doc_id {kind}, lang_pred string, score double, log_prob double")
