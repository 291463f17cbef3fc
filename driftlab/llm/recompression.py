"""Substring dedup over words by recompression.

Words become 64-bit names. A round names every maximal run of one name (run compression) and
then every pair of a left and a right name, sides being a hash bit of the name and the round (pair
compression). A name is a hash of what it stands for, so all tasks give equal strings equal
names without exchanging a dictionary. Each symbol carries the span of words that settles it:
its own words and those of the neighbours that a round looked at. Wherever that span occurs in the corpus
the same symbol stands at the same place, so a window of words holds the same settled symbols
wherever it occurs. A window is filed under its settled symbol of the highest round, the leftmost
of them; the file key is the hash of that symbol's whole settled span. The first word of a
window is always settled, so every window has a key.

1. Every document's keys; a key is shared if two documents have it. A task folds its own chunk
   first, so a passage that a third of all documents hold leaves a chunk once.
2. Documents with shared keys make 128-bit BLAKE2 digests of the words of just the windows filed under them;
   of the documents of a chunk that have a window, all but the one
   of smallest id are settled at once, and one row per window and chunk is exchanged to find the smallest id overall.
3. Covered words are cut out of the text.

Names and keys only choose the windows to look at: a collision there costs work. What is removed is
decided by the digests of the words themselves, for which no two inputs of equal digest can be constructed.

Copies of a whole text are represented by their smallest id in step 2; the others lose all words
that any window covers.

Defined cases: null text has no words; texts shorter than a window are left whole; a null id counts
as larger than all others (two of them in the order of a hash of their texts, equal texts as one document); ids of 2^62 and
above raise an error; an empty table gives an empty result; rows
that repeat an id are one document for the comparison, and each row is cut.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import NO_ID, SpanHash, as_text, byte_hash, chunks, cut, mix64, ship, signed, stand_in, text_buffer, word_spans

_U = np.uint64
_FAR = np.int64(1) << np.int64(40)


class Symbols:
    """Symbols of one round: name, first and last word (exclusive), settling span, document."""

    __slots__ = ("doc", "lo", "hi", "name")

    def __init__(self, name, lo, hi, doc):
        self.name, self.lo, self.hi, self.doc = name, lo, hi, doc


def _neighbours(s: Symbols) -> tuple[np.ndarray, np.ndarray]:
    """Settling span's start of the symbol before, and end of the one after; far away at a document's edge."""
    before = np.full(len(s.name), -_FAR)
    after = np.full(len(s.name), _FAR)
    if len(s.name) > 1:
        same = s.doc[1:] == s.doc[:-1]
        before[1:] = np.where(same, s.lo[:-1], -_FAR)
        after[:-1] = np.where(same, s.hi[1:], _FAR)
    return before, after


def compress_runs(s: Symbols, level: int) -> Symbols:
    """One symbol for each maximal run of a name; both neighbours settle it."""
    n = len(s.name)
    fresh = np.ones(n, bool)
    fresh[1:] = (s.name[1:] != s.name[:-1]) | (s.doc[1:] != s.doc[:-1])
    first = np.flatnonzero(fresh)
    last = np.append(first[1:], n) - 1
    before, after = _neighbours(s)
    length = (last - first + 1).astype(_U)
    name = s.name[first]
    with np.errstate(over="ignore"):
        name = np.where(length > 1, mix64(name + length * _U(0x9FB21C651E98DF25) + _U(level)), name)
    return Symbols(name, np.minimum(s.lo[first], before[first]), np.maximum(s.hi[last], after[last]), s.doc[first])


def compress_pairs(s: Symbols, level: int) -> Symbols:
    """One symbol for each pair of a left name and a right name; a single symbol is settled by the neighbour it could have paired with."""
    n = len(s.name)
    with np.errstate(over="ignore"):
        left = (mix64(s.name + _U(level) * _U(0xC2B2AE3D27D4EB4F)) & _U(1)).astype(bool)
    joins = np.zeros(n, bool)
    joins[:-1] = left[:-1] & ~left[1:] & (s.doc[1:] == s.doc[:-1])
    eaten = np.zeros(n, bool)
    eaten[1:] = joins[:-1]
    before, after = _neighbours(s)
    lo = np.where(left | eaten, s.lo, np.minimum(s.lo, before))
    hi = np.where(~left | joins, s.hi, np.maximum(s.hi, after))
    partner = np.flatnonzero(joins)
    name = s.name.copy()
    with np.errstate(over="ignore"):
        name[partner] = mix64(mix64(s.name[partner] + _U(2 * level + 1)) + s.name[partner + 1])
    hi[partner] = np.maximum(s.hi[partner], s.hi[partner + 1])
    lo[partner] = np.minimum(s.lo[partner], s.lo[partner + 1])
    keep = ~eaten
    return Symbols(name[keep], lo[keep], hi[keep], s.doc[keep])


def window_keys(words: np.ndarray, doc: np.ndarray, first: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray]:
    """(start word of every window inside one document, its file key). first: first word number of each document, and the end."""
    n = len(words)
    size = np.diff(first)
    starts = np.flatnonzero(np.arange(n) + window <= first[1:][doc]) if n else np.zeros(0, np.int64)
    key = np.zeros(len(starts), _U)
    if not len(starts):
        return starts, key
    spans = SpanHash(words, 1)
    at = np.arange(n, dtype=np.int64)
    s = Symbols(words, at, at + 1, doc)
    held, level = [], 0
    while True:
        fits = s.hi - s.lo <= window
        if not fits.any():
            break
        lo, hi = s.lo[fits], s.hi[fits]
        held.append((lo, hi))
        level += 1
        s = compress_pairs(compress_runs(s, level), level)
    del size
    open_ = np.arange(len(starts))
    for level in range(len(held) - 1, -1, -1):
        lo, hi = held[level]
        p = starts[open_]
        at = np.searchsorted(lo, p)
        good = at < len(lo)
        good[good] = hi[at[good]] <= p[good] + window
        where, which = open_[good], at[good]
        with np.errstate(over="ignore"):
            key[where] = mix64(spans.of(lo[which], hi[which]) + _U(level))
        open_ = open_[~good]
        if not len(open_):
            break
    return starts, key


class WordChunk:
    """The words of a run of documents: spans, names, document numbers."""

    def __init__(self, flat: np.ndarray, offsets: np.ndarray):
        self.start, self.end, self.doc = word_spans(flat, offsets)
        self.name = byte_hash(flat, 1).of(self.start, self.end)
        self.first = np.searchsorted(self.doc, np.arange(len(offsets)))
        self.flat = flat

    def digests(self, first: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray]:
        """128-bit digests, as two longs, of the `window` words from each word of `first` on, joined by one blank."""
        length = self.end - self.start
        stop = np.cumsum(length + 1)
        joined = np.full(int(stop[-1]) if len(stop) else 0, 0x20, np.uint8)
        begin = stop - length - 1
        at = np.arange(int(length.sum())) - np.repeat(np.cumsum(length) - length, length)
        joined[np.repeat(begin, length) + at] = self.flat[np.repeat(self.start, length) + at]
        raw = memoryview(joined.tobytes())
        spans = zip(begin[first].tolist(), (stop[first + window - 1] - 1).tolist(), strict=True)
        out = np.frombuffer(b"".join([hashlib.blake2b(raw[s:e], digest_size=16).digest() for s, e in spans]), np.int64).reshape(-1, 2)
        return out[:, 0], out[:, 1]


def _id_array(column: pa.Array) -> np.ndarray:
    return column.to_numpy(zero_copy_only=False).astype(np.int64)


def _first_of(order_key: np.ndarray) -> np.ndarray:
    """Marks the first element of each run of equal values."""
    out = np.ones(len(order_key), bool)
    out[1:] = order_key[1:] != order_key[:-1]
    return out


def _key_rows(window: int):
    """(key, doc_id, salt, shared): shared already if another document of the chunk has the key."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids = _id_array(b.column(0))
            flat, off = text_buffer(b.column(1))
            for i, j in chunks(off):
                a = off[i]
                c = WordChunk(flat[a : off[j]], off[i : j + 1] - a)
                starts, key = window_keys(c.name, c.doc, c.first, window)
                if not len(starts):
                    continue
                fresh = np.ones(len(key), bool)
                d = c.doc[starts]
                fresh[1:] = (key[1:] != key[:-1]) | (d[1:] != d[:-1])
                key, who = key[fresh], ids[i:j][d[fresh]]
                order = np.lexsort((who, key))
                key, who = key[order], who[order]
                lead = _first_of(key)
                both = lead | _first_of(who)
                key, who, lead = key[both], who[both], lead[both]
                at = np.flatnonzero(lead)
                many = np.diff(np.append(at, len(key))) > 1
                shared = np.repeat(many, np.diff(np.append(at, len(key))))
                # a row that does not lead is settled, and groups with nothing
                salt = np.where(lead, np.int64(-1), who)
                yield pa.RecordBatch.from_arrays([pa.array(signed(key)), pa.array(who), pa.array(salt), pa.array(shared)], names=["key", "doc_id", "salt", "shared"])

    return run


def _window_rows(window: int):
    """Per document and its shared keys: settled windows, and one open row per window and chunk."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            names = b.schema.names
            ids = _id_array(b.column(names.index("doc_id")))
            lists = b.column(names.index("keys")).cast(pa.large_list(pa.int64()))
            flat, off = text_buffer(b.column(names.index("text")))
            # lists may be null: offsets then repeat
            koff, kval = lists.offsets.to_numpy(), lists.values.to_numpy(zero_copy_only=False).view(np.uint64)
            live = np.diff(koff) > 0
            for i, j in chunks(off):
                if not live[i:j].any():
                    continue
                a = off[i]
                c = WordChunk(flat[a : off[j]], off[i : j + 1] - a)
                starts, key = window_keys(c.name, c.doc, c.first, window)
                d = c.doc[starts]
                # (document, key) pairs that are shared
                held = np.repeat(np.arange(j - i), np.diff(koff[i : j + 1]))
                with np.errstate(over="ignore"):
                    tag = mix64(kval[koff[i] : koff[j]] + held.astype(_U) * _U(0x9E3779B97F4A7C15))
                    own = mix64(key + d.astype(_U) * _U(0x9E3779B97F4A7C15))
                hit = np.isin(own, tag)
                starts, d = starts[hit], d[hit]
                if not len(starts):
                    continue
                f1, f2 = c.digests(starts, window)
                who = ids[i:j][d]
                place = (starts - c.first[d]).astype(np.int32)
                order = np.lexsort((place, who, f2, f1))
                f1, f2, who, place = f1[order], f2[order], who[order], place[order]
                lead = _first_of(f1) | _first_of(f2)
                smallest = who[np.maximum.accumulate(np.where(lead, np.arange(len(lead)), 0))]
                later = who > smallest
                # open: one row per window, of the chunk's smallest id; settled: one row per document
                for settled in (False, True):
                    at = np.flatnonzero(later == settled)
                    if settled:
                        at = at[np.argsort(who[at], kind="stable")]
                        head = np.flatnonzero(_first_of(who[at]))
                    else:
                        head = np.flatnonzero(lead[at])
                    if not len(at):
                        continue
                    first = at[head]
                    places = pa.ListArray.from_arrays(pa.array(np.append(head, len(at)).astype(np.int32)), pa.array(place[at]))
                    tag = (who[first], np.zeros(len(first), np.int64)) if settled else (f1[first], f2[first])
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(first), settled)), pa.array(tag[0]), pa.array(tag[1]), pa.array(who[first]), places], names=["settled", "f1", "f2", "doc_id", "places"])

    return run


def _cut_rows(window: int):
    """doc_id, n_words, n_removed, removed (ranges), kept text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            names = b.schema.names
            flat, off = text_buffer(b.column(names.index("text")))
            raw = flat.tobytes()
            copies = b.column(names.index("copy")).to_pylist()
            places = b.column(names.index("places"))
            rows: list = []
            for r in range(b.num_rows):
                words = raw[off[r] : off[r + 1]].split()
                n = len(words)
                gone = np.zeros(n + 1, np.int64)
                if copies[r] and n >= window:
                    gone[0] += 1
                    gone[n] -= 1
                elif places[r].is_valid:
                    p = places[r].values.to_numpy(zero_copy_only=False)
                    np.add.at(gone, p, 1)
                    np.add.at(gone, p + window, -1)
                cover = np.cumsum(gone[:n]) > 0
                if cover.any():
                    edge = np.flatnonzero(np.diff(np.concatenate([[0], cover.view(np.int8), [0]])))
                    words = [w for w, c in zip(words, cover.tolist(), strict=True) if not c]
                    spans = edge.tolist()
                else:
                    spans = []
                rows.append((n, int(cover.sum()), spans, b" ".join(words)))
            yield pa.RecordBatch.from_arrays(
                [
                    b.column(names.index("doc_id")),
                    pa.array([r[0] for r in rows], pa.int64()),
                    pa.array([r[1] for r in rows], pa.int64()),
                    pa.array([r[2] for r in rows], pa.list_(pa.int64())),
                    pa.array([hashlib.sha256(r[3]).hexdigest() for r in rows], pa.string()),
                    pa.array([r[3].decode() for r in rows], pa.string()),
                ],
                names=["doc_id", "n_words", "n_removed", "removed", "kept_sha256", "kept_text"],
            )

    return run


def cut_repeats(docs: DataFrame, window: int = 50, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_words, n_removed, removed (word ranges: start, end, start, end, ...), kept_sha256, kept_text.

    A word goes if a window of `window` words that covers it also starts in a document of smaller id.
    """
    ship(docs.sparkSession)
    texts = as_text(docs.select(stand_in(id_col, text_col), F.col(text_col).cast("string").alias("text")))
    # whole copies: the smallest id speaks for the text
    digest = texts.select("doc_id", F.sha2("text", 256).alias("digest"))
    # written, so that the join below meets plain exchanges, which the adaptive skew join can split
    low = cut(digest.groupBy("digest").agg(F.min("doc_id").alias("rep"), F.count("*").alias("n")).where("n > 1"))
    copies = digest.join(low, "digest").where("doc_id <> rep").select("doc_id", F.lit(True).alias("copy")).distinct()

    keys = texts.mapInArrow(_key_rows(window), "key long, doc_id long, salt long, shared boolean")
    at = Window.partitionBy("key", "salt")
    spread = F.col("shared") | (F.min("doc_id").over(at) != F.max("doc_id").over(at)) | F.max("shared").over(at)
    shared = keys.withColumn("spread", spread).where("spread").groupBy("doc_id").agg(F.collect_list("key").alias("keys"))
    # a copy is settled already and asks for no window
    asked = shared.join(copies, "doc_id", "left_anti")
    rows = texts.join(asked, "doc_id", "left").select("doc_id", "text", "keys").mapInArrow(_window_rows(window), "settled boolean, f1 long, f2 long, doc_id long, places array<int>")
    by = Window.partitionBy("settled", "f1", "f2")
    found = rows.withColumn("low", F.min("doc_id").over(by)).where(F.col("settled") | (F.col("doc_id") > F.col("low")))
    places = found.groupBy("doc_id").agg(F.flatten(F.collect_list("places")).alias("places"))
    marks = places.join(copies, "doc_id", "full")
    out = texts.join(marks, "doc_id", "left").select("doc_id", "text", "places", "copy").mapInArrow(
        _cut_rows(window), "doc_id long, n_words long, n_removed long, removed array<long>, kept_sha256 string, kept_text string"
    )
    return out.withColumn("doc_id", F.when(F.col("doc_id") < NO_ID, F.col("doc_id")))
