"""SentencePiece encoding and decoding: batched Viterbi over a fixed piece vocabulary.

Words of equal length advance together.  For every start and length the hash of the substring is
looked up among the sorted piece keys, then one vectorised maximum per end position keeps the best
score and the length of its last piece (the backpointer).

Defined results: null text has null ids; the empty text has none; characters without a piece become
the bytes of their UTF-8 form; a literal U+2581 is written as bytes so that decoding gives back
exactly the input; on a tie the longer last piece wins.  Repeated rows, very long texts and extra
columns need no care: rows are independent and only the named columns are read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from pairlattice.llm.common import list_array, slices, tidy

SPACE = "▁"
MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)
#: Code point that stands for a literal U+2581 of the text; no piece holds it.
LITERAL_SPACE = 0x110000
#: Natural-log penalty of a character that no piece covers, below the least piece.
UNKNOWN_PENALTY = 10.0
BITMAP_BITS = 20
CACHE_WORDS = 300_000


def default_model() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def cells_of(keys: np.ndarray) -> np.ndarray:
    """The cell of each key; mixed once more, since those of single characters have no high bits."""
    return (keys * MULTIPLIER >> np.uint64(64 - BITMAP_BITS)).astype(np.int64)


@dataclass
class PieceTable:
    """Pieces, scores and hash keys sorted by cell; its size is that of the vocabulary."""

    pieces: list[str]
    raw: list[bytes]
    scores: np.ndarray
    byte_ids: np.ndarray
    keys: np.ndarray
    key_ids: np.ndarray
    codes: np.ndarray
    longest: int
    bitmap: np.ndarray
    unknown: float
    #: Where the keys of each cell of the bitmap begin, and the most keys of a cell.
    first: np.ndarray
    most: int

    @classmethod
    def build(cls, pieces: list[str], scores: list[float], byte_ids: dict[int, int], usable: list[bool]) -> PieceTable:
        longest = max((len(p) for p, u in zip(pieces, usable) if u), default=1)
        ids = np.array([i for i, u in enumerate(usable) if u], np.int64)
        codes = np.full((len(pieces), longest), -1, np.int64)
        keys = np.zeros(len(ids), np.uint64)
        for k, i in enumerate(ids):
            c = np.array([ord(x) for x in pieces[i]], np.int64)
            codes[i, : len(c)] = c
            h = np.uint64(0)
            with np.errstate(over="ignore"):
                for x in c:
                    h = h * MULTIPLIER + np.uint64(x + 1)
                keys[k] = h ^ (h >> np.uint64(29))
        order = np.lexsort((keys, cells_of(keys)))
        keys, ids = keys[order], ids[order]
        if len(keys) > 1 and (keys[1:] == keys[:-1]).any():
            raise ValueError("two pieces share a hash key")
        cell = cells_of(keys)
        bitmap, first = np.zeros(1 << BITMAP_BITS, bool), np.zeros(1 << BITMAP_BITS, np.int32)
        bitmap[cell] = True
        first[cell[::-1]] = np.arange(len(keys), dtype=np.int32)[::-1]
        bytes_of = {i: bytes([b]) for b, i in byte_ids.items()}
        raw = [bytes_of.get(i, p.replace(SPACE, " ").encode()) for i, p in enumerate(pieces)]
        s = np.array(scores, np.float64)
        least = s[ids].min() if len(ids) else 0.0
        return cls(pieces, raw, s, np.array([byte_ids[b] for b in range(256)], np.int64), keys, ids, codes, longest, bitmap, float(least) - UNKNOWN_PENALTY, first, int(np.bincount(cell).max(initial=0)) if len(cell) else 0)

    @classmethod
    def load(cls, path: str | None = None, limit: int | None = None) -> PieceTable:
        """Read a .model file.

        A model of merges holds ranks instead of log probabilities; those become a Zipf law,
        log p = -log((rank + 2) * sum of 1 / (rank + 2)).  Pieces of white space alone but for one
        space, and pieces with a space inside, are for decoding only, so words are independent.
        ``limit`` keeps the first pieces (and single characters) only.
        """
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path or default_model())
        n = model.get_piece_size()
        pieces = [model.id_to_piece(i) for i in range(n)]
        byte_ids = {int(pieces[i][3:5], 16): i for i in range(n) if model.is_byte(i)}
        usable = [not (model.is_byte(i) or model.is_control(i) or model.is_unknown(i) or model.is_unused(i)) and SPACE not in p[1:] for i, p in enumerate(pieces)]
        given = [model.get_score(i) for i in range(n)]
        ranked = all(float(x).is_integer() for x in given)
        if ranked:
            mass = np.log(sum(1 / (2 - x) for x, u in zip(given, usable) if u))
            given = [float(-np.log(2 - x) - mass) if x <= 0 else 0.0 for x in given]
        if limit is not None:
            usable = [u and (i < limit or len(pieces[i]) == 1) for i, u in enumerate(usable)]
        return cls.build(pieces, given, byte_ids, usable)

    def spans(self, codes: np.ndarray) -> list[np.ndarray]:
        """For each length l, the piece id (or -1) of every substring [s, s + l) of words of one length."""
        n, size = codes.shape
        out, h = [], np.zeros((n, size), np.uint64)
        c = (codes + 1).astype(np.uint64)
        for length in range(1, min(self.longest, size) + 1):
            h = h[:, : size - length + 1] * MULTIPLIER + c[:, length - 1 :]
            key = h ^ (h >> np.uint64(29))
            cell = cells_of(key)
            rows, at = np.nonzero(self.bitmap.take(cell))
            found = np.full(key.shape, -1, np.int32)
            if len(rows):
                probe, k = key[rows, at], self.first.take(cell[rows, at])
                for _ in range(self.most - 1):  # keys of a cell ascend; one of the next cell is no probe
                    np.minimum(k + (self.keys.take(k) < probe), len(self.keys) - 1, out=k, casting="unsafe")
                hit = self.keys.take(k) == probe
                rows, at, ids = rows[hit], at[hit], self.key_ids[k[hit]]
                same = np.ones(len(ids), bool)  # equal hashes are compared as text too
                for j in range(length):
                    same &= self.codes[ids, j] == codes[rows, at + j]
                if length < self.longest:
                    same &= self.codes[ids, length] == -1
                found[rows[same], at[same]] = ids[same]
            out.append(found)
        return out

    def viterbi(self, codes: np.ndarray) -> list[list[int]]:
        """Best pieces of each word; ``codes`` has a word of the same length in each row."""
        n, size = codes.shape
        found = self.spans(codes)
        best, back = np.zeros((size + 1, n)), np.zeros((n, size + 1), np.int16)
        for end in range(1, size + 1):
            top, step = np.full(n, -np.inf), np.ones(n, np.int16)
            for k in range(min(len(found), end), 0, -1):  # the longest of equals
                ids = found[k - 1][:, end - k]
                if k == 1:
                    at, score = slice(None), best[end - 1] + np.where(ids >= 0, self.scores.take(ids), self.unknown)
                else:
                    at = np.flatnonzero(ids >= 0)
                    if not len(at):
                        continue
                    score = best[end - k, at] + self.scores.take(ids[at])
                more = score > top[at]
                at = at[more] if k > 1 else np.flatnonzero(more)
                top[at], step[at] = score[more], k
            best[end], back[:, end] = top, step
        out = []
        for i in range(n):
            ids, end, row = [], size, back[i]
            while end:
                k = int(row[end])
                p = int(found[k - 1][i, end - k])
                if p < 0:
                    c = int(codes[i, end - 1])
                    ids.extend(self.byte_ids[b] for b in reversed((SPACE if c == LITERAL_SPACE else chr(c)).encode("utf-8", "surrogatepass")))
                else:
                    ids.append(p)
                end -= k
            out.append(ids[::-1])
        return out

    def encode_words(self, words: list[str], leading: bool, rows: int = 4096, cells: int = 1 << 18) -> dict[str, bytes]:
        """Ids of each word as little-endian 32-bit integers; ``leading`` puts the space mark before it."""
        by_length: dict[int, list[str]] = {}
        for w in words:
            by_length.setdefault(len(w) + leading, []).append(w)
        out = {}
        for size, same in by_length.items():
            step = max(1, min(rows, cells // max(size, 1)))
            for k in range(0, len(same), step):
                part = same[k : k + step]
                if not size:
                    out.update((w, b"") for w in part)
                    continue
                codes = np.frombuffer("".join(part).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64).reshape(len(part), -1)
                codes = np.where(codes == ord(SPACE), LITERAL_SPACE, codes)
                if leading:
                    codes = np.concatenate([np.full((len(part), 1), ord(SPACE), np.int64), codes], 1)
                out.update((w, np.array(ids, "<i4").tobytes()) for w, ids in zip(part, self.viterbi(codes)))
        return out


class Encoder:
    """Encodes texts with a bounded memory of words already seen."""

    def __init__(self, table: PieceTable):
        self.table = table
        self.bare: dict[str, bytes] = {}
        self.spaced: dict[str, bytes] = {}
        self.line = np.array([table.byte_ids[10]], "<i4").tobytes()

    def learn(self, known: dict[str, bytes], words: set[str], leading: bool) -> None:
        new = [w for w in words if w not in known]
        if len(known) + len(new) > CACHE_WORDS:
            known.clear()
            new = list(words)
        known.update(self.table.encode_words(new, leading))

    def encode(self, texts: list[str | None]) -> list[np.ndarray]:
        lines = [[line.split(" ") for line in t.split("\n")] if t else [] for t in texts]
        bare, spaced = set(), set()
        for doc in lines:
            for k, words in enumerate(doc):
                if k:
                    bare.add(words[0])
                    spaced.update(words[1:])
                else:
                    spaced.update(words)
        self.learn(self.bare, bare, False)
        self.learn(self.spaced, spaced, True)
        out = []
        b, s = self.bare.__getitem__, self.spaced.__getitem__
        for doc in lines:
            parts: list[bytes] = []
            for k, words in enumerate(doc):
                if k:
                    parts.append(self.line)
                    parts.append(b(words[0]))
                    parts.extend(map(s, words[1:]))
                else:
                    parts.extend(map(s, words))
            out.append(np.frombuffer(b"".join(parts), "<i4"))
        return out

    def decode(self, ids: list[int]) -> str:
        text = b"".join(map(self.table.raw.__getitem__, ids)).decode("utf-8", "surrogatepass")
        return text[1:] if text[:1] == " " else text


def encode(docs: DataFrame, table: PieceTable | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_tokens, ids, decoded_sha256, round_trip) of each row; one narrow pass, no shuffle.

    ``decoded_sha256`` is the digest of the text decoded from ``ids``; ``round_trip`` tells whether
    that text equals the input (a null text: ids null, round_trip true).
    """
    table = table or PieceTable.load()
    kind = dict(docs.dtypes)[id_col]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = Encoder(table)
        for batch in batches:
            texts = batch.column(1).to_pylist()
            for lo, hi in slices(texts):
                part = texts[lo:hi]
                ids = enc.encode(part)
                back = [enc.decode(x.tolist()) for x in ids]
                counts = np.array([len(x) for x in ids], np.int64)
                lists = list_array(np.concatenate(ids) if ids else np.zeros(0, np.int32), counts, pa.int32())
                nulls = [t is None for t in part]
                if any(nulls):
                    lists = pa.ListArray.from_arrays(lists.offsets, lists.values, mask=pa.array(nulls))
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(lo, hi - lo), pa.array(counts, pa.int64()), lists, pa.array([hashlib.sha256(x.encode("utf-8", "surrogatepass")).hexdigest() for x in back]), pa.array([x == (t or "") for x, t in zip(back, part)])],
                    names=["id", "n_tokens", "ids", "decoded_sha256", "round_trip"],
                )

    return docs.select(id_col, text_col).mapInArrow(tidy(run), f"`{id_col}` {kind}, n_tokens long, ids array<int>, decoded_sha256 string, round_trip boolean")


def decode(encoded: DataFrame, table: PieceTable | None = None, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """(id, text) from ids; null ids give null text.  Bytes that are no UTF-8 raise."""
    table = table or PieceTable.load()
    kind = dict(encoded.dtypes)[id_col]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = Encoder(table)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([None if x is None else enc.decode(x) for x in batch.column(1).to_pylist()], pa.string())], names=["id", "text"])

    return encoded.select(id_col, ids_col).mapInArrow(tidy(run), f"`{id_col}` {kind}, text string")
