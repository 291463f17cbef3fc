"""Repeated byte strings found by a common-prefix-aware distributed merge sort of suffixes.

A byte is removed if some string of `length` bytes that covers it also starts elsewhere. Only
suffixes that can tell are sorted: every window of `length` bytes is filed under one anchor, the
place in its first half whose 16 bytes hash smallest (leftmost on ties). The choice depends on the window's content
alone, so equal windows lie at the same offset around their anchors, and the suffixes at the
anchors share at least the half window. As in prefix-doubling string sorting, a first exchange of
64-bit hashes of that guaranteed prefix drops the suffixes that no other suffix can match; a task
folds its own chunk first, so a passage of a third of all documents leaves a chunk once.

The other suffixes are sorted in each task into runs, identical suffixes (with identical left
context) folded into one entry with a list of places. A run is front-coded: each entry carries
the length of the prefix it shares with the one before it, and the rest. Runs are exchanged by a
hash of the guaranteed prefix. A receiving task merges its runs in a loser tree whose players carry
the length of the prefix they share with the last suffix put out: unequal lengths decide a match at once,
equal lengths start the comparison behind the known prefix. The merge yields the suffixes in
order with their common-prefix lengths; stretches that share the guaranteed prefix are classes, and
in a class a window at offset a before the anchor repeats if two entries share a bytes to the
left and length - a to the right, which the common-prefix lengths of both sides tell exactly.

Hot classes are split before the exchange: a prefix that more than `HOT` documents share has its windows dealt by
bands of `BAND` offsets, and each band's suffix starts so far before the anchor that all but BAND - 1 bytes of its windows are the guaranteed
prefix, whose hash deals it. Equal windows have one offset, so one band and one bucket; a passage met in
many surroundings falls into as many classes as its surroundings differ. A suffix that a task holds twice has told all it
can: its places are put out at once, dealt evenly, and the run carries it without them.

Whole copies: one row of each text takes part, and a text that several rows have is removed where any window covers it.

Defined cases: null text is empty; texts shorter than `length` are left whole; rows with null ids
are documents like any other; repeated rows are copies of each other; an empty table gives an
empty result. Different texts have different ids, below 2^62 (others raise an error). Hashes of bytes only choose the
suffixes to sort; whether texts are one is told by BLAKE2 and SHA-256 digests, whether windows are by comparing bytes.
"""

from __future__ import annotations

import hashlib
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import NO_ID, as_text, byte_hash, chunks, cut, mix64, ship, signed, stand_in, text_buffer

_U = np.uint64
GRAM = 16
#: Bytes of suffix text that a task sorts into one run.
RUN_BYTES = 12 << 20
#: Documents that share a guaranteed prefix before its class is split by bands of offsets, and the offsets of a band.
HOT = 1000
BAND = 16
#: Tasks that the documents of a hot key are dealt to when they are told that it is hot.
SALTS = 64


def common_prefix(a: bytes, b: bytes, known: int = 0) -> int:
    """Length of the common prefix of a and b, of which `known` bytes need no comparison."""
    top = min(len(a), len(b))
    if a[known:top] == b[known:top]:
        return top
    lo, step = known, 8
    while a[lo : lo + step] == b[lo : lo + step]:
        lo += step
        step *= 2
    hi = min(lo + step, top)
    while lo < hi:
        mid = (lo + hi) // 2
        if a[lo : mid + 1] == b[lo : mid + 1]:
            lo = mid + 1
        else:
            hi = mid
    return lo


def anchors(flat: np.ndarray, offsets: np.ndarray, length: int) -> tuple[np.ndarray, ...]:
    """(place, first window, last window, document, key) of each anchor of a chunk; the key hashes the guaranteed prefix."""
    n, half = len(flat), length // 2
    none = tuple(np.zeros(0, np.int64) for _ in range(4)) + (np.zeros(0, _U),)
    if n < length:
        return none
    doc = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))
    valid = np.flatnonzero(np.arange(n) + length <= offsets[1:][doc])
    if not len(valid):
        return none
    sums = byte_hash(flat, 1)
    gram = min(GRAM, length - half)
    at = np.arange(n - gram + 1)
    ranked = (sums.of(at, at + gram) & _U(0xFFFFFFFF00000000)) | at.astype(_U)
    pad = -len(ranked) % half
    blocks = np.concatenate([ranked, np.full(pad, ~_U(0))]).reshape(-1, half)
    ahead = np.minimum.accumulate(blocks, axis=1).ravel()
    back = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    best = (np.minimum(back[valid], ahead[valid + half - 1]) & _U(0xFFFFFFFF)).astype(np.int64)
    fresh = np.ones(len(best), bool)
    fresh[1:] = best[1:] != best[:-1]
    lead = np.flatnonzero(fresh)
    tail = np.append(lead[1:], len(best)) - 1
    place = best[lead]
    return place, valid[lead], valid[tail], doc[place], sums.of(place, place + length - half + 1)


def _key_rows(length: int):
    """(key, doc_id, salt, shared, what): what tells occurrences in different texts or places apart."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids = b.column(0).to_numpy(zero_copy_only=False)
            flat, off = text_buffer(b.column(1))
            for i, j in chunks(off):
                a = off[i]
                part, inner = flat[a : off[j]], off[i : j + 1] - a
                place, _, _, doc, key = anchors(part, inner, length)
                if not len(place):
                    continue
                raw = memoryview(part.tobytes())
                live = np.unique(doc)
                text = np.zeros(len(inner) - 1, _U)
                text[live] = np.frombuffer(b"".join([hashlib.blake2b(raw[s:e], digest_size=8).digest() for s, e in zip(inner[live].tolist(), inner[live + 1].tolist(), strict=True)]), _U)
                with np.errstate(over="ignore"):
                    what = mix64(text[doc] + (place - inner[doc]).astype(_U))
                order = np.lexsort((what, key))
                key, what, who = key[order], what[order], ids[i:j][doc[order]]
                lead = np.ones(len(key), bool)
                lead[1:] = key[1:] != key[:-1]
                at = np.flatnonzero(lead)
                size = np.diff(np.append(at, len(key)))
                shared = np.repeat(what[at] != what[at + size - 1], size)
                # copies inside the chunk fold into the leading row; a shared key is kept for each document
                keep = lead | shared
                yield pa.RecordBatch.from_arrays(
                    [pa.array(signed(key[keep])), pa.array(who[keep]), pa.array(np.where(lead, np.int64(-1), who)[keep]), pa.array(shared[keep]), pa.array(signed(what[keep]))],
                    names=["key", "doc_id", "salt", "shared", "what"],
                )

    return run


class Run:
    """A sorted, front-coded run of suffixes. Entries: right bytes, left bytes (reversed), first and last offset, place.

    An entry with several places is known to repeat: it is written without them, and read with none.
    """

    @staticmethod
    def encode(entries: list[tuple[bytes, bytes, int, int, list[tuple[int, int]]]]) -> bytes:
        head, tails, places = [], [], []
        right = left = b""
        for r, l, lo, hi, where in entries:
            kr, kl = common_prefix(right, r), common_prefix(left, l)
            head.append((kr, len(r), kl, len(l), lo, hi, len(where) == 1))
            tails += [r[kr:], l[kl:]]
            if len(where) == 1:
                places += where
            right, left = r, l
        table = np.array(head, np.int32).reshape(-1, 7)
        spots = np.array(places, np.int64).reshape(-1, 2)
        return b"".join([np.array([len(table), len(spots)], np.int64).tobytes(), np.ascontiguousarray(table.T).tobytes(), np.ascontiguousarray(spots.T).tobytes(), *tails])

    @staticmethod
    def decode(blob: bytes) -> Iterator[tuple[int, bytes, bytes, int, int, list[tuple[int, int]]]]:
        """(prefix shared with the entry before, right, left, first, last offset, places), in order."""
        n, m = np.frombuffer(blob, np.int64, 2).tolist()
        table = np.frombuffer(blob, np.int32, 7 * n, 16).reshape(7, n).T.tolist()
        spots = np.frombuffer(blob, np.int64, 2 * m, 16 + 28 * n).reshape(2, m).T.tolist()
        at, spot = 16 + 28 * n + 16 * m, 0
        right = left = b""
        for kr, nr, kl, nl, lo, hi, k in table:
            right = right[:kr] + blob[at : at + nr - kr]
            at += nr - kr
            left = left[:kl] + blob[at : at + nl - kl]
            at += nl - kl
            yield kr, right, left, lo, hi, spots[spot : spot + k]
            spot += k


class LoserTree:
    """Merges front-coded runs. A player is [shared prefix with the last output, entry, run]; None has run out."""

    def __init__(self, runs: list[Iterator]):
        self.runs = runs
        self.size = 1 << max(0, (len(runs) - 1).bit_length())
        players = [self._next(i) for i in range(len(runs))] + [None] * (self.size - len(runs))
        for p in players:
            if p is not None:
                p[0] = 0  # nothing is out yet
        self.losers: list = [None] * self.size
        level = players
        at = self.size
        while at > 1:
            at //= 2
            winners = []
            for k in range(at):
                won, lost = self._match(level[2 * k], level[2 * k + 1])
                winners.append(won)
                self.losers[at + k] = lost
            level = winners
        self.winner = level[0]

    def _next(self, i: int):
        entry = next(self.runs[i], None)
        return None if entry is None else [entry[0], entry, i]

    @staticmethod
    def _match(a, b):
        """(winner, loser); the loser then holds the prefix it shares with the winner."""
        if b is None:
            return a, b
        if a is None:
            return b, a
        if a[0] != b[0]:
            return (a, b) if a[0] > b[0] else (b, a)
        x, y = a[1][1], b[1][1]
        k = common_prefix(x, y, a[0])
        if x[k : k + 1] <= y[k : k + 1]:
            b[0] = k
            return a, b
        a[0] = k
        return b, a

    def __iter__(self) -> Iterator[tuple[int, tuple]]:
        """(prefix shared with the suffix put out before, entry)."""
        losers, size, match = self.losers, self.size, self._match
        while self.winner is not None:
            shared, entry, run = self.winner
            yield shared, entry
            player = self._next(run)
            at = (run + size) // 2
            while at:
                player, losers[at] = match(player, losers[at])
                at //= 2
            self.winner = player


def bands(raw: bytes, x: int, first: int, last: int, length: int) -> Iterator[tuple[int, bytes, bytes, int, int, int]]:
    """(hash of the guaranteed prefix, right, left, first, last offset, place) of each band of the windows first..last before anchor x."""
    wide = band_width(length)
    lo, hi = x - last, x - first
    for low in range(lo - lo % wide, hi + 1, wide):
        a, b, y = max(lo, low), min(hi, low + wide - 1), x - low
        yield zlib.crc32(raw[y : y + length - wide + 1], low), raw[y : x - a + length], raw[x - b : y][::-1], a - low, b - low, y


def band_width(length: int) -> int:
    return max(1, min(BAND, length // 4))


def _sorted_runs(length: int, buckets: int):
    """Suffixes at shared anchors, sorted and front-coded per task and bucket.

    Buckets below `buckets` are of whole classes, the next as many of bands of hot ones, those behind hold places (doc_id, start, end) that are settled.
    """

    def flush(held: list[list], turn: int) -> pa.RecordBatch | None:
        ids, blobs, settled = [], [], []
        for bucket, part in enumerate(held):
            if not part:
                continue
            part.sort()
            folded: list = []
            for r, l, lo, hi, d, x in part:
                if folded and folded[-1][0] == r and folded[-1][1] == l:
                    folded[-1][4].append((d, x))
                else:
                    folded.append((r, l, lo, hi, [(d, x)]))
            settled += [(d, x - hi, x - lo + length) for _, _, lo, hi, where in folded if len(where) > 1 for d, x in where]
            ids.append(bucket)
            blobs.append(Run.encode(folded))
            part.clear()
        if settled:
            ids.append(2 * buckets + turn % buckets)
            blobs.append(np.array(settled, np.int64).tobytes())
        return pa.RecordBatch.from_arrays([pa.array(ids, pa.int32()), pa.array(blobs, pa.binary())], names=["bucket", "run"]) if ids else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list] = [[] for _ in range(2 * buckets)]
        weight, turn = 0, uuid.uuid4().int % buckets
        for b in batches:
            names = b.schema.names
            ids = b.column(names.index("doc_id")).to_pylist()
            lists = b.column(names.index("keys")).cast(pa.large_list(pa.int64()))
            koff, kval = lists.offsets.to_numpy(), lists.values.to_numpy(zero_copy_only=False).view(np.uint64)
            often = b.column(names.index("hot")).cast(pa.large_list(pa.int64()))
            hoff, hval = often.offsets.to_numpy(), often.values.to_numpy(zero_copy_only=False).view(np.uint64)
            flat, off = text_buffer(b.column(names.index("text")))
            for i, j in chunks(off):
                if koff[i] == koff[j]:
                    continue
                a = off[i]
                part, inner = flat[a : off[j]], off[i : j + 1] - a
                place, first, last, doc, key = anchors(part, inner, length)
                own = _tags(key, doc)
                hit = np.flatnonzero(np.isin(own, _tags(kval[koff[i] : koff[j]], np.repeat(np.arange(j - i), np.diff(koff[i : j + 1])))))
                hot = np.isin(own[hit], _tags(hval[hoff[i] : hoff[j]], np.repeat(np.arange(j - i), np.diff(hoff[i : j + 1]))))
                raw = part.tobytes()
                cells = (mix64(key[hit]) % _U(buckets)).tolist()
                starts = inner[doc[hit]].tolist()
                for cell, x, f, l, d, s, split in zip(cells, place[hit].tolist(), first[hit].tolist(), last[hit].tolist(), doc[hit].tolist(), starts, hot.tolist(), strict=True):
                    if split:
                        for h, right, left, lo, hi, y in bands(raw, x, f, l, length):
                            held[buckets + h % buckets].append((right, left, lo, hi, ids[i + d], y - s))
                            weight += length + 80
                        continue
                    # a window at p covers [p, p + length); the anchor's own bytes reach length - (x - l) to the right
                    held[cell].append((raw[x : l + length], raw[f:x][::-1], x - l, x - f, ids[i + d], x - s))
                    weight += l - f + length + 80
                if weight >= RUN_BYTES:
                    out = flush(held, turn)
                    weight, turn = 0, turn + 1
                    if out:
                        yield out
        out = flush(held, turn)
        if out:
            yield out

    return run


def _tags(key: np.ndarray, doc: np.ndarray) -> np.ndarray:
    """One number for a key in a document of a chunk."""
    with np.errstate(over="ignore"):
        return mix64(key + doc.astype(_U) * _U(0x9E3779B97F4A7C15))


def repeated_offsets(entries: list, shared: list[int], length: int) -> list[list[tuple[int, int]]]:
    """For each distinct entry of a class (right, left, lo, hi, n_places), in order of right: ranges of offsets whose window repeats.

    shared[i] is the prefix that entries i - 1 and i share to the right.
    """
    n = len(entries)
    out: list[list[tuple[int, int]]] = [[] for _ in range(n)]
    if n <= 6:
        for i, (_, _, lo, hi, k) in enumerate(entries):
            if k > 1:
                out[i] = [(lo, hi)]
        for i in range(n):
            right = length
            for j in range(i + 1, n):
                right = min(right, shared[j])
                left = common_prefix(entries[i][1], entries[j][1])
                for e in (i, j):
                    lo, hi = max(entries[e][2], length - right), min(entries[e][3], left)
                    if lo <= hi:
                        out[e].append((lo, hi))
        return out
    rights = np.array(shared, np.int64)
    rights[0] = -1
    order = sorted(range(n), key=lambda i: entries[i][1])
    lefts = np.array([-1] + [common_prefix(entries[a][1], entries[b][1]) for a, b in zip(order, order[1:], strict=False)], np.int64)
    order = np.array(order)
    lo, hi, many = (np.array([e[k] for e in entries]) for k in (2, 3, 4))
    low, high = int(lo.min()), int(hi.max())
    hits = np.zeros((n, high - low + 1), bool)
    for a in range(low, high + 1):
        right_class = np.cumsum(rights < length - a)
        left_class = np.empty(n, np.int64)
        left_class[order] = np.cumsum(lefts < a)
        _, back, count = np.unique(left_class * (n + 1) + right_class, return_inverse=True, return_counts=True)
        hits[:, a - low] = ((count[back] > 1) | (many > 1)) & (lo <= a) & (a <= hi)
    for i in range(n):
        edge = np.flatnonzero(np.diff(np.concatenate([[0], hits[i].view(np.int8), [0]])))
        out[i] = [(low + int(s), low + int(e) - 1) for s, e in edge.reshape(-1, 2)]
    return out


def _merge(length: int, buckets: int):
    """Merges a bucket's runs; puts out (doc_id, start, end) of removed bytes."""

    def bucket_rows(bucket: int, blobs: list[bytes]) -> Iterator[tuple[list, list, list]]:
        prefix = length - length // 2 + 1 if bucket < buckets else length - band_width(length) + 1
        docs, starts, ends = [], [], []
        group: list = []
        shared: list[int] = []

        def close() -> None:
            if len(group) < 2:  # alone, or settled where it was sorted
                return
            # entries with the same right and left context are one, wherever they stand among equal rights
            distinct: dict = {}
            merged, links, least = [], [], length
            for k, (r, l, lo, hi, where) in zip(shared, group, strict=True):
                least = min(least, k)
                e = distinct.get((r, l))
                if e is None:
                    distinct[(r, l)] = [r, l, lo, hi, list(where), 1 if where else 2]
                    merged.append(distinct[(r, l)])
                    links.append(least)
                    least = length
                else:
                    e[4].extend(where)
                    e[5] = 2
            for e, ranges in zip(merged, repeated_offsets([(*e[:4], e[5]) for e in merged], links, length), strict=True):
                for lo, hi in ranges:
                    for d, x in e[4]:
                        docs.append(d)
                        starts.append(x - hi)
                        ends.append(x - lo + length)

        for k, (_, r, l, lo, hi, where) in LoserTree([Run.decode(x) for x in blobs]):
            if k < prefix:
                close()
                group, shared = [], []
            group.append((r, l, lo, hi, where))
            shared.append(k)
            if len(docs) > 50_000:
                yield docs, starts, ends
                docs, starts, ends = [], [], []
        close()
        yield docs, starts, ends

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, blobs = None, []

        def done() -> Iterator[pa.RecordBatch]:
            for d, s, e in bucket_rows(at, blobs):
                if d:
                    yield pa.RecordBatch.from_arrays([pa.array(d, pa.int64()), pa.array(s, pa.int64()), pa.array(e, pa.int64())], names=["doc_id", "start", "end"])

        for b in batches:
            for bucket, blob in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                if bucket >= 2 * buckets:
                    yield pa.RecordBatch.from_arrays([pa.array(c) for c in np.frombuffer(blob, np.int64).reshape(-1, 3).T.copy()], names=["doc_id", "start", "end"])
                    continue
                if bucket != at and blobs:
                    yield from done()
                    blobs = []
                at = bucket
                blobs.append(blob)
        if blobs:
            yield from done()

    return run


def _cut_rows(length: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            names = b.schema.names
            flat, off = text_buffer(b.column(names.index("text")))
            raw = flat.tobytes()
            copies = b.column(names.index("copy")).to_pylist()
            spans = b.column(names.index("spans")).to_pylist()
            sizes, gone, runs, ranges, digest, kept = [], [], [], [], [], []
            for r in range(b.num_rows):
                text = raw[off[r] : off[r + 1]]
                n = len(text)
                cuts: list[list[int]] = []
                if copies[r] and n >= length:
                    cuts = [[0, n]]
                elif spans[r]:
                    for s, e in sorted((x["start"], x["end"]) for x in spans[r]):
                        if cuts and s <= cuts[-1][1]:
                            cuts[-1][1] = max(cuts[-1][1], e)
                        else:
                            cuts.append([s, e])
                edges = [0, *(x for c in cuts for x in c), n]
                rest = b"".join(text[s:e] for s, e in zip(edges[::2], edges[1::2], strict=True))
                sizes.append(n)
                gone.append(n - len(rest))
                runs.append(len(cuts))
                ranges.append([x for c in cuts for x in c])
                digest.append(hashlib.sha256(rest).hexdigest())
                kept.append(rest)
            yield pa.RecordBatch.from_arrays(
                [b.column(names.index("doc_id")), pa.array(sizes, pa.int64()), pa.array(gone, pa.int64()), pa.array(runs, pa.int64()), pa.array(ranges, pa.list_(pa.int64())), pa.array(digest, pa.string()), pa.array(kept, pa.binary())],
                names=["doc_id", "n_bytes", "n_removed", "n_spans", "removed", "kept_sha256", "kept"],
            )

    return run


def cut_repeated_bytes(docs: DataFrame, length: int = 400, id_col: str = "doc_id", text_col: str = "text", buckets: int | None = None) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, removed (byte ranges: start, end, ...), kept_sha256, kept (bytes; a cut may split a character)."""
    spark = docs.sparkSession
    ship(spark)
    buckets = buckets or max(16, 2 * int(spark.conf.get("spark.sql.shuffle.partitions", "200")))
    texts = as_text(docs.select(stand_in(id_col, text_col), F.col(text_col).cast("string").alias("text")))
    digest = texts.select("doc_id", F.sha2("text", 256).alias("digest"))
    # written, so that the join below meets plain exchanges, which the adaptive skew join can split
    low = cut(digest.groupBy("digest").agg(F.min("doc_id").alias("rep"), F.count("*").alias("n")).where("n > 1"))
    copies = digest.join(low, "digest").select("doc_id", F.lit(True).alias("copy"), (F.col("doc_id") == F.col("rep")).alias("speaks")).groupBy("doc_id", "copy").agg(F.max("speaks").alias("speaks"))

    keys = texts.mapInArrow(_key_rows(length), "key long, doc_id long, salt long, shared boolean, what long")
    at = Window.partitionBy("key", "salt")
    spread = F.col("shared") | (F.min("what").over(at) != F.max("what").over(at)) | F.max("shared").over(at)
    # written once: its keys are counted and listed
    listed = cut(keys.withColumn("spread", spread).where("spread").select("key", "doc_id"))
    hot = listed.groupBy("key").agg(F.count("*").alias("rows")).where(F.col("rows") > HOT).select("key", F.col("key").alias("hot"))
    # hot keys are few, at most one in HOT rows: each stands in SALTS places, among which its documents are dealt
    hot = hot.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1)))).withColumn("salt", F.col("salt").cast("long"))
    listed = listed.withColumn("salt", F.pmod(F.xxhash64("doc_id"), F.lit(SALTS))).join(hot, ["key", "salt"], "left").groupBy("doc_id").agg(F.collect_set("key").alias("keys"), F.collect_set("hot").alias("hot"))
    # the row that speaks for a text may not be the row that led its chunk: keys of copies go to it
    rows = digest.join(low, "digest").select("doc_id", "rep")
    flat = lambda c: F.array_distinct(F.flatten(F.collect_list(c))).alias(c)
    asked = listed.join(rows, "doc_id", "left").groupBy(F.coalesce("rep", "doc_id").alias("doc_id")).agg(flat("keys"), flat("hot"))
    runs = texts.join(asked, "doc_id", "left").select("doc_id", "text", "keys", "hot").mapInArrow(_sorted_runs(length, buckets), "bucket int, run binary")
    spans = runs.repartition(buckets, "bucket").sortWithinPartitions("bucket").mapInArrow(_merge(length, buckets), "doc_id long, start long, end long")
    by_doc = spans.groupBy("doc_id").agg(F.collect_list(F.struct("start", "end")).alias("spans"))
    marks = by_doc.join(copies.select("doc_id", "copy"), "doc_id", "full")
    out = texts.join(marks, "doc_id", "left").select("doc_id", "text", "spans", "copy").mapInArrow(
        _cut_rows(length), "doc_id long, n_bytes long, n_removed long, n_spans long, removed array<long>, kept_sha256 string, kept binary"
    )
    return out.withColumn("doc_id", F.when(F.col("doc_id") < NO_ID, F.col("doc_id")))
