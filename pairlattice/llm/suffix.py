"""Exact substring dedup by suffix sorting with a difference cover.

A byte is removed when a string of ``length`` bytes that covers it also starts in a document with a
smaller id.  Three steps:

1. *What can repeat.*  Every string of ``length`` bytes has a least hash among its ``gram``-byte
   pieces; consecutive strings with the same least hash form a run.  Equal strings have equal hashes
   wherever they stand, so a run whose hash no other document has cannot repeat.  Hashes go to parts
   by their leading bits, packed by the block of documents; a part answers which of them two
   documents hold.  Nothing that repeats is lost here.
2. *Suffix sorting.*  The bytes of the runs that are left meet in the parts of their hashes.  Each
   part sorts the suffixes of its distinct stretches with the difference cover of period three:
   sampled triples are sorted and named, the names are sorted recursively, the other suffixes are
   merged in.  Neighbours in that order whose prefixes of ``length`` bytes are equal make a class,
   and the least document of the class is known to all its members.
3. *Removal.*  Covered bytes of each document are joined into maximal runs.

Equal texts are found by digest first; only the one with the least id takes part, all others are
covered whole.  A stretch that several documents of a block hold is sent once with their ids.

Defined results: null text is empty; texts shorter than ``length`` lose nothing; repeated rows, and
several texts under one id, get a row each and do not remove one another; an empty table gives no
rows; further columns are ignored; matches never cross texts.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairlattice.llm.common import cut, parts_for, release, slices, text_bytes, tidy, unused

ODD = 0x9E3779B97F4A7C15
MIX = np.uint64(0xD6E8FEB86659FD93)
KEEP_BITS = np.uint64(16)
#: Stands for a null id.
NO_ID = -(1 << 62)


@dataclass(frozen=True)
class Settings:
    length: int = 50
    #: Bytes of a piece; the longer, the fewer chance repeats and the more runs.
    gram: int = 24
    #: Payload that a part of the first step may hold, about.
    part_bytes: int = 3 << 20
    #: Bytes of stretches that a part of the second step may hold, about; suffix sorting takes some hundred times as much memory.
    sort_bytes: int = 1 << 20
    #: Copies up to this number are kept out of the first step by broadcasting their ids.
    broadcast_copies: int = 500_000


# ---- suffix sorting -------------------------------------------------------------------------


def names_of(*columns: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
    """Order of rows by their columns, each row's name (rank of its value, from 1) and the number of names."""
    key = pack(columns)
    order = np.argsort(key, kind="stable")
    s = key[order]
    new = np.ones(len(s), bool)
    new[1:] = s[1:] != s[:-1]
    name = np.empty(len(s), np.int64)
    name[order] = np.cumsum(new)
    return order, name, int(new.sum())


def pack(columns: tuple[np.ndarray, ...]) -> np.ndarray:
    """One integer for each row that sorts as its columns do."""
    key, bits = columns[0], int(columns[0].max(initial=0)).bit_length()
    for c in columns[1:]:
        more = int(c.max(initial=0)).bit_length()
        if bits + more > 62:
            key = np.unique(key, return_inverse=True)[1].astype(np.int64)
            bits = int(key.max(initial=0)).bit_length()
        key, bits = (key << np.int64(more)) | c, bits + more
    return key


def suffix_array(symbols: np.ndarray) -> np.ndarray:
    """Starts of the suffixes of a sequence of positive integers in lexicographic order."""
    n = len(symbols)
    if n < 3:
        return np.array(sorted(range(n), key=lambda i: symbols[i:].tolist()), np.int64)
    s = np.concatenate([symbols.astype(np.int64), np.zeros(4, np.int64)])
    # sample: starts 1 and 2 modulo 3; one start past the end keeps the halves apart
    first, second = np.arange(1, n + (n % 3 == 1), 3), np.arange(2, n, 3)
    sample = np.concatenate([first, second])
    order, name, kinds = names_of(s[sample], s[sample + 1], s[sample + 2])
    if kinds < len(sample):
        order = suffix_array(name)
    sample_sorted = sample[order]
    rank = np.zeros(n + 4, np.int64)
    rank[sample_sorted] = np.arange(1, len(sample_sorted) + 1)
    sample_sorted = sample_sorted[sample_sorted < n]
    rest = np.arange(0, n, 3)
    rest = rest[np.argsort(pack((s[rest], rank[rest + 1])), kind="stable")]
    # where each of the rest goes among the sample of either kind
    ones, twos = sample_sorted[sample_sorted % 3 == 1], sample_sorted[sample_sorted % 3 == 2]

    def before(others: np.ndarray, columns) -> np.ndarray:
        both = np.concatenate([others, rest])
        key = pack(columns(both))
        return np.searchsorted(key[: len(others)], key[len(others) :], "left")

    at = np.arange(len(rest)) + before(ones, lambda i: (s[i], rank[i + 1])) + before(twos, lambda i: (s[i], s[i + 1], rank[i + 2]))
    out = np.empty(n, np.int64)
    taken = np.zeros(n, bool)
    taken[at] = True
    out[at] = rest
    out[~taken] = sample_sorted
    return out


def repeated_classes(text: np.ndarray, starts: np.ndarray, ends: np.ndarray, owner: np.ndarray, length: int) -> np.ndarray:
    """For every position of ``text`` the least owner among all stretches that hold the string starting there.

    ``text`` is bytes in which the stretches [starts, ends) follow one another, each closed by a
    separator; positions with fewer than ``length`` bytes left get a large value.
    """
    far = np.iinfo(np.int64).max
    out = np.full(len(text), far, np.int64)
    order = suffix_array(text)
    which = np.repeat(np.arange(len(starts)), ends - starts + 1)
    left = ends[which] - np.arange(len(text))
    order = order[left[order] >= length]
    if not len(order):
        return out
    wide = np.zeros(len(text) + 8, np.uint64)
    wide[: len(text)] = text
    word = np.zeros(len(text), np.uint64)  # eight symbols at a time, exactly: a byte and its separator fit nine bits, seven of them 63
    for j in range(7):
        word = (word << np.uint64(9)) | wide[j : j + len(text)]
    same = np.ones(len(order) - 1, bool)
    for j in [*range(0, length - 7, 7), length - 7]:
        same &= word[order[1:] + j] == word[order[:-1] + j]
    begin = np.concatenate([[0], np.nonzero(~same)[0] + 1])
    least = np.minimum.reduceat(owner[which[order]], begin)
    out[order] = np.repeat(least, np.diff(np.concatenate([begin, [len(order)]])))
    return out


# ---- runs -----------------------------------------------------------------------------------


def hashes(text: np.ndarray, gram: int) -> np.ndarray:
    """Hash of the ``gram`` bytes at every position, by doubling."""
    n = len(text) - gram + 1
    power = lambda k: np.uint64(pow(ODD, k, 1 << 64))
    level, size, done, out = text.astype(np.uint64) + np.uint64(1), 1, 0, None
    rest = gram
    while rest:
        if rest & 1:
            piece = level[done : done + n]
            out = piece.copy() if out is None else out * power(size) + piece
            done += size
        rest >>= 1
        if rest:
            level = level[:-size] * power(size) + level[size:]
            size *= 2
    out = (out ^ (out >> np.uint64(32))) * MIX
    return out ^ (out >> np.uint64(29))


def least_of(h: np.ndarray, window: int) -> np.ndarray:
    """Minimum of every ``window`` neighbours."""
    size, low = 1, h
    while size * 2 <= window:
        low = np.minimum(low[:-size], low[size:])
        size *= 2
    return np.minimum(low[: len(h) - window + 1], low[window - size :]) if size < window else low


def runs(texts: list[bytes], settings: Settings) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(doc, hash, first, last): runs of strings with the same least hash, in text order; hashes keep 48 bits."""
    flat = np.frombuffer(b"".join(texts), np.uint8)
    size = np.array([len(t) for t in texts], np.int64)
    begin = np.concatenate([[0], np.cumsum(size)[:-1]]) if len(size) else size
    none = np.zeros(0, np.int64)
    if len(flat) < settings.length:
        return none, none.astype(np.uint64), none, none
    low = least_of(hashes(flat, settings.gram), settings.length - settings.gram + 1)
    low = (low ^ (low >> np.uint64(32))) * MIX  # minima crowd near zero; parts need even values
    low = (low ^ (low >> np.uint64(29))) >> KEEP_BITS
    doc = np.repeat(np.arange(len(texts)), size)[: len(low)]
    inside = np.arange(len(low)) + settings.length <= (begin + size)[doc]
    new = np.ones(len(low), bool)
    new[1:] = (low[1:] != low[:-1]) | (doc[1:] != doc[:-1])
    edge = np.flatnonzero(new | ~inside)
    last = np.concatenate([edge[1:], [len(low)]]) - 1
    ok = inside[edge]
    edge, last = edge[ok], last[ok]
    d = doc[edge]
    return d, low[edge], edge - begin[d], last - begin[d]


def part_of(h: np.ndarray, parts: int) -> np.ndarray:
    return ((h >> np.uint64(16)) * np.uint64(parts) >> np.uint64(32)).astype(np.int64)


def pack48(h: np.ndarray) -> bytes:
    return np.ascontiguousarray(h.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :6]).tobytes()


def unpack48(data: bytes) -> np.ndarray:
    out = np.zeros((len(data) // 6, 8), np.uint8)
    out[:, :6] = np.frombuffer(data, np.uint8).reshape(-1, 6)
    return out.view("<u8").ravel()


def groups(key: np.ndarray) -> list[tuple[int, int]]:
    """Ranges of equal values in a sorted array."""
    edge = np.concatenate([[0], np.flatnonzero(key[1:] != key[:-1]) + 1, [len(key)]]) if len(key) else np.zeros(1, int)
    return list(zip(edge[:-1].tolist(), edge[1:].tolist()))


RUN_ROWS = "part int, known boolean, docs binary, keys binary, counts binary, hashes binary"


def offer(reps: DataFrame, parts: int, settings: Settings) -> DataFrame:
    """Packed hashes of the runs by part; what two documents of a block share is already known."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, keys, texts = np.array(batch.column(0).to_pylist(), np.int64), np.array(batch.column(1).to_pylist(), np.int64), batch.column(2).to_pylist()
            for lo, hi in slices(texts, 1 << 20):
                doc, h, _, _ = runs([t.encode("utf-8", "surrogatepass") for t in texts[lo:hi]], settings)
                rows = []
                if len(h):
                    # one entry for a document and hash
                    order = np.lexsort((doc, h))
                    doc, h = doc[order], h[order]
                    once = np.ones(len(h), bool)
                    once[1:] = (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])
                    doc, h = doc[once], h[once]
                    name = ids[lo:hi][doc]
                    edge = np.concatenate([[True], h[1:] != h[:-1]])
                    start = np.flatnonzero(edge)
                    several = np.minimum.reduceat(name, start) != np.maximum.reduceat(name, start)
                    known = np.repeat(several, np.diff(np.concatenate([start, [len(h)]])))
                    ask = ~known | edge  # of a shared hash one entry goes on
                    for kind, chosen in ((False, ask), (True, known)):
                        d, x = doc[chosen], h[chosen]
                        p = part_of(x, parts)
                        order = np.lexsort((d, p))
                        d, x, p = d[order], x[order], p[order]
                        for a, b in groups(p):
                            who, n = np.unique(d[a:b], return_counts=True)
                            rows.append((int(p[a]), kind, ids[lo:hi][who].tobytes(), keys[lo:hi][who].tobytes(), n.astype(np.int32).tobytes(), pack48(x[a:b])))
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int32(), pa.bool_(), pa.binary(), pa.binary(), pa.binary(), pa.binary()))], names=["part", "known", "docs", "keys", "counts", "hashes"])

    return reps.select("doc_id", "key", "text").mapInArrow(tidy(run), RUN_ROWS)


def shared(offered: DataFrame) -> DataFrame:
    """(doc_id, key, hashes): the hashes of each document that another document holds too."""

    def resolve(table: pa.Table) -> pa.Table:
        release()
        doc, key, h, known = [], [], [], []
        for k, d, t, n, x in zip(*(table.column(c).to_pylist() for c in ("known", "docs", "keys", "counts", "hashes"))):
            n = np.frombuffer(n, np.int32)
            doc.append(np.repeat(np.frombuffer(d, np.int64), n))
            key.append(np.repeat(np.frombuffer(t, np.int64), n))
            h.append(unpack48(x))
            known.append(np.full(len(h[-1]), k))
        doc, key, h, known = (np.concatenate(x) for x in (doc, key, h, known))
        order = np.argsort(h, kind="stable")
        start = np.flatnonzero(np.concatenate([[True], h[order][1:] != h[order][:-1]]))
        several = np.minimum.reduceat(doc[order], start) != np.maximum.reduceat(doc[order], start)
        keep = np.zeros(len(h), bool)
        keep[order] = np.repeat(several, np.diff(np.concatenate([start, [len(h)]])))
        keep |= known
        doc, key, h = doc[keep], key[keep], h[keep]
        order = np.lexsort((key, doc))
        doc, key, h = doc[order], key[order], h[order]
        new = np.flatnonzero(np.concatenate([[True], (doc[1:] != doc[:-1]) | (key[1:] != key[:-1])])) if len(doc) else np.zeros(0, int)
        cut = np.concatenate([new, [len(doc)]])
        return pa.table({"doc_id": pa.array(doc[new]), "key": pa.array(key[new]), "hashes": pa.array([pack48(np.unique(h[a:b])) for a, b in zip(cut[:-1], cut[1:])], pa.binary())})

    return offered.groupBy("part").applyInArrow(resolve, "doc_id long, key long, hashes binary")


STRETCH_ROWS = "part int, docs binary, keys binary, owners binary, firsts binary, sizes binary, bytes binary"


def stretches(found: DataFrame, parts: int, settings: Settings) -> DataFrame:
    """The bytes of the runs with a shared hash, packed by part; equal stretches of a batch are sent once.

    ``owners`` tells the stretch of each (document, first byte); ``sizes`` the bytes of each stretch.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, keys, texts = np.array(batch.column(0).to_pylist(), np.int64), np.array(batch.column(1).to_pylist(), np.int64), batch.column(2).to_pylist()
            wanted = batch.column(3).to_pylist()
            held: dict[int, tuple[dict[bytes, int], list[np.ndarray], list[int], list[np.ndarray]]] = {}
            for lo, hi in slices(texts, 1 << 19):
                data = [t.encode("utf-8", "surrogatepass") for t in texts[lo:hi]]
                doc, h, first, last = runs(data, settings)
                if not len(h):
                    continue
                begin = np.concatenate([np.searchsorted(doc, np.arange(hi - lo)), [len(doc)]])
                hit = np.concatenate([np.isin(h[begin[i] : begin[i + 1]], unpack48(b"".join(wanted[lo + i]))) for i in range(hi - lo)])
                doc, first, last, p = doc[hit], first[hit], last[hit], part_of(h[hit], parts)
                order = np.argsort(p, kind="stable")
                doc, first, last, p = doc[order], first[order], last[order], p[order]
                for a, b in groups(p):
                    seen, who, owner, starts = held.setdefault(int(p[a]), ({}, [], [], []))
                    owner.extend(seen.setdefault(data[d][x : y + settings.length], len(seen)) for d, x, y in zip(doc[a:b].tolist(), first[a:b].tolist(), last[a:b].tolist()))
                    who.append(doc[a:b] + lo)
                    starts.append(first[a:b])
            rows = []
            for part, (seen, who, owner, starts) in held.items():
                at = np.concatenate(who)
                rows.append((part, ids[at].tobytes(), keys[at].tobytes(), np.array(owner, np.int32).tobytes(), np.concatenate(starts).astype(np.int32).tobytes(), np.array([len(x) for x in seen], np.int32).tobytes(), b"".join(seen)))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int32(), *[pa.binary()] * 6))], names=["part", "docs", "keys", "owners", "firsts", "sizes", "bytes"])

    return found.select("doc_id", "key", "text", "wanted").mapInArrow(tidy(run), STRETCH_ROWS)


def covered(packed: DataFrame, settings: Settings) -> DataFrame:
    """(doc_id, key, spans): byte ranges of each document that strings of earlier documents cover."""

    def resolve(table: pa.Table) -> pa.Table:
        release()
        docs, keys, firsts, which = [], [], [], []
        seen: dict[bytes, int] = {}
        for d, t, o, f, n, x in zip(*(table.column(c).to_pylist() for c in ("docs", "keys", "owners", "firsts", "sizes", "bytes"))):
            ends = np.cumsum(np.frombuffer(n, np.int32)).tolist()
            local = np.array([seen.setdefault(x[a:b], len(seen)) for a, b in zip([0, *ends], ends)], np.int64)
            docs.append(np.frombuffer(d, np.int64))
            keys.append(np.frombuffer(t, np.int64))
            firsts.append(np.frombuffer(f, np.int32))
            which.append(local[np.frombuffer(o, np.int32)])
        docs, keys, firsts, which = (np.concatenate(x) for x in (docs, keys, firsts, which))
        size = np.array([len(x) for x in seen], np.int64)
        least = np.full(len(seen), np.iinfo(np.int64).max)
        np.minimum.at(least, which, docs)
        # one separator closes each stretch; bytes become 1 to 256, the separator is 257
        begin = np.concatenate([[0], np.cumsum(size)[:-1]])
        start = begin + np.arange(len(size))
        text = np.full(int(size.sum()) + len(size), 257, np.int64)
        inside = np.ones(len(text), bool)
        inside[start + size] = False
        text[inside] = np.frombuffer(b"".join(seen), np.uint8).astype(np.int64) + 1
        earliest = repeated_classes(text, start, start + size, least, settings.length)[inside]
        # strings of each occurrence that an earlier document holds
        count = size[which] - settings.length + 1
        at = np.repeat(begin[which] - np.concatenate([[0], np.cumsum(count)[:-1]]), count) + np.arange(int(count.sum()))
        gone = earliest[at] < np.repeat(docs, count)
        entry = np.repeat(np.arange(len(docs)), count)[gone]
        pos = (firsts[entry] + (at - begin[which][np.repeat(np.arange(len(docs)), count)])[gone]) if len(entry) else np.zeros(0, np.int64)
        order = np.lexsort((pos, keys[entry], docs[entry]))
        d, k, pos = docs[entry][order], keys[entry][order], pos[order]
        new = np.ones(len(pos), bool)
        new[1:] = (pos[1:] > pos[:-1] + settings.length) | (d[1:] != d[:-1]) | (k[1:] != k[:-1])
        start = np.flatnonzero(new)
        last = np.concatenate([start[1:], [len(pos)]]) - 1 if len(pos) else start
        spans = np.stack([pos[start], pos[last] + settings.length], 1).astype(np.int32) if len(pos) else np.zeros((0, 2), np.int32)
        sd, sk = d[start], k[start]
        cut = np.flatnonzero(np.concatenate([[True], (sd[1:] != sd[:-1]) | (sk[1:] != sk[:-1])])) if len(sd) else np.zeros(0, int)
        edge = np.concatenate([cut, [len(sd)]])
        return pa.table({"doc_id": pa.array(sd[cut], pa.int64()), "key": pa.array(sk[cut], pa.int64()), "spans": pa.array([spans[a:b].tobytes() for a, b in zip(edge[:-1], edge[1:])], pa.binary())})

    return packed.groupBy("part").applyInArrow(resolve, "doc_id long, key long, spans binary")


def merged(spans: list[bytes] | None) -> list[tuple[int, int]]:
    """Maximal runs of the union of packed spans."""
    if not spans:
        return []
    s = np.frombuffer(b"".join(spans), np.int32).reshape(-1, 2)
    s = s[np.argsort(s[:, 0], kind="stable")]
    reach = np.maximum.accumulate(s[:, 1])
    new = np.flatnonzero(np.concatenate([[True], s[1:, 0] > reach[:-1]]))
    return list(zip(s[new, 0].tolist(), reach[np.concatenate([new[1:], [len(s)]]) - 1].tolist()))


def marked(docs: DataFrame, settings: Settings | None = None) -> tuple[DataFrame, str, str, str]:
    """``docs`` with three columns, and their names: the id as a long, a list of packed ranges (or null), whether an earlier document has the same text."""
    settings = settings or Settings()
    doc, key, list_, copied = (unused(docs, c) for c in ("_doc", "_key", "_spans", "_copy"))
    # no key is null, so no filter is inferred on either side, and both joins below read the same exchange of the
    # texts, as long as they take its columns in the same order
    own = F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID))
    named = docs.withColumns({doc: own, key: F.xxhash64("text")})
    bytes_, digest_of = F.coalesce(F.octet_length("text"), F.lit(0)), F.md5(F.coalesce("text", F.lit("")))
    total = text_bytes(docs)
    parts = parts_for(total * 0.6, settings.part_bytes)
    digest = named.where(bytes_ >= settings.length).select(F.col(doc).alias("_doc"), digest_of.alias("digest"))
    copies = digest.groupBy("digest").agg(F.min("_doc").alias("least"), F.max("_doc").alias("most")).where("least < most")
    copies = digest.join(copies, "digest").where("_doc > least").select("_doc", "digest").distinct()
    cd, cg, d, k = (unused(named, c) for c in ("_cd", "_cg", "_d", "_k"))
    copies = cut(copies.select(F.col("_doc").alias(cd), F.col("digest").alias(cg)))
    flags = F.broadcast(copies) if copies.count() <= settings.broadcast_copies else copies
    copy = (F.col(doc) == F.col(cd)) & (digest_of == F.col(cg))
    reps = named.where(bytes_ >= settings.length).join(flags, copy, "left_anti").select(F.col(doc).alias("doc_id"), F.col(key).alias("key"), "text")
    wanted = shared(offer(reps, parts, settings)).groupBy("doc_id", "key").agg(F.collect_set("hashes").alias("wanted"))
    same = (F.col(doc) == F.col(d)) & (F.col(key) == F.col(k))
    found = named.select("text", doc, key).join(wanted.withColumnsRenamed({"doc_id": d, "key": k}), same)
    found = found.select(F.col(doc).alias("doc_id"), F.col(key).alias("key"), "text", "wanted")
    spans = covered(stretches(found, parts_for(total, settings.sort_bytes), settings), settings).groupBy("doc_id", "key").agg(F.collect_list("spans").alias(list_))
    out = named.join(spans.withColumnsRenamed({"doc_id": d, "key": k}), same, "left").drop(d, k)
    out = out.join(flags, copy, "left")
    return out.withColumn(copied, F.col(cd).isNotNull()).drop(cd, cg, key), doc, list_, copied


def digests(docs: DataFrame, settings: Settings | None = None) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256) of each row."""
    kind = dict(docs.dtypes)["doc_id"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for text, spans, copy in zip(*(batch.column(i).to_pylist() for i in range(1, 4))):
                data = text.encode("utf-8", "surrogatepass") if text else b""
                cuts = [(0, len(data))] if copy else merged(spans)
                kept, at = hashlib.sha256(), 0
                for a, b in cuts:
                    kept.update(data[at:a])
                    at = b
                kept.update(data[at:])
                rows.append((len(data), sum(b - a for a, b in cuts), len(cuts), kept.hexdigest()))
            cols = list(zip(*rows)) or [[], [], [], []]
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.int64(), pa.string())))], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    found, doc, list_, copied = marked(docs.select("doc_id", "text"), settings)
    found = found.select(F.nullif(doc, F.lit(NO_ID)).cast(kind).alias("doc_id"), "text", list_, copied)
    return found.mapInArrow(tidy(run), f"doc_id {kind}, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def kept_text(docs: DataFrame, settings: Settings | None = None) -> DataFrame:
    """``docs`` with the covered parts taken out of ``text``; a character goes when all its bytes are covered."""

    def strip(data: bytes, cuts: list[tuple[int, int]]) -> str:
        out, at = [], 0
        for a, b in cuts:
            while a < len(data) and data[a] & 0xC0 == 0x80:  # a character that is not covered from its first byte stays
                a += 1
            while b < len(data) and b > 0 and data[b] & 0xC0 == 0x80:  # nor one that is not covered to its last
                b -= 1
            if b > a:
                out.append(data[at:a])
                at = b
        out.append(data[at:])
        return b"".join(out).decode("utf-8", "surrogatepass")

    names = docs.columns
    found, _, list_, copied = marked(docs, settings)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = {c: i for i, c in enumerate(batch.schema.names)}
            new = []
            for text, spans, copy in zip(*(batch.column(at[c]).to_pylist() for c in ("text", list_, copied))):
                data = text.encode("utf-8", "surrogatepass") if text else b""
                new.append(text if text is None else strip(data, [(0, len(data))] if copy else merged(spans)))
            yield pa.RecordBatch.from_arrays([pa.array(new, pa.string()) if c == "text" else batch.column(at[c]) for c in names], names=names)

    return found.mapInArrow(tidy(run), docs.schema)


def oracle(length: int = 50) -> str:
    """The digests in DuckDB SQL: every string of the table with its least document."""
    return f"""
WITH d AS (SELECT doc_id, encode(coalesce(text, '')) AS b FROM documents),
h AS (SELECT doc_id, hex(b) AS x, octet_length(b) AS n FROM d),
s AS (SELECT doc_id, x, n, unnest(range(0, n - {length} + 1)) AS i FROM h WHERE n >= {length}),
w AS (SELECT doc_id, i, substr(x, 2 * i + 1, {2 * length}) AS g FROM s),
m AS (SELECT doc_id, i, min(doc_id) OVER (PARTITION BY g) AS least FROM w),
r AS (SELECT DISTINCT doc_id, i FROM m WHERE least < doc_id),
e AS (SELECT doc_id, i, CASE WHEN i <= lag(i) OVER (PARTITION BY doc_id ORDER BY i) + {length} THEN 0 ELSE 1 END AS new FROM r),
q AS (SELECT doc_id, i, sum(new) OVER (PARTITION BY doc_id ORDER BY i) AS run FROM e),
p AS (SELECT doc_id, run, min(i) AS a, max(i) + {length} AS z FROM q GROUP BY 1, 2),
k AS (SELECT doc_id, run, a, z, lag(z, 1, 0) OVER (PARTITION BY doc_id ORDER BY run) AS from_, last_value(z) OVER (PARTITION BY doc_id ORDER BY run ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS tail FROM p),
t AS (SELECT k.doc_id, count(*) AS n_spans, sum(z - a) AS n_removed,
        string_agg(substr(x, CAST(2 * from_ + 1 AS BIGINT), CAST(2 * (a - from_) AS BIGINT)), '' ORDER BY run) || substr(any_value(x), CAST(2 * any_value(tail) + 1 AS BIGINT)) AS kept
      FROM k JOIN h USING (doc_id) GROUP BY k.doc_id)
SELECT h.doc_id, CAST(n AS BIGINT) AS n_bytes, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, CAST(coalesce(n_spans, 0) AS BIGINT) AS n_spans,
  sha256(CASE WHEN t.doc_id IS NULL THEN b ELSE unhex(kept) END) AS kept_sha256
FROM h JOIN d USING (doc_id) LEFT JOIN t USING (doc_id)
"""
