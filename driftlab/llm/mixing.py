"""Mixing sources to target weights by Sainte-Lague apportionment of equal-token blocks.

A source's target in words is turned into a whole number of blocks of `block_words` words: all
sources compete for the blocks of the mix by highest quotients target / (2 * seats + 1). Each
source's quota is then apportioned, by the same rule, among its shards (hash classes of its
documents, so a hot source becomes many shards). In a shard the documents lie end to end in a seeded order, on a tape
that is closed to a ring: every block has the same number of words, a block over the end going on at the
beginning. So a shard's quota is a number of whole passes over the ring and the words of the blocks left, from the seeded beginning
on. What whole blocks miss of a source's target (less than a few blocks) is added to, or taken from, its
largest shards as a short block, so a source gives its rounded target exactly, however small it is. What a
document gives follows from its place on the tape, so no block is ever materialised.

Sources and shards are the only things on the driver: (name, words) rows. A source has one shard for
every `shard_words` words, or, where that makes more than `max_shards` shards in all, for every max_shards-th part of all
words; so the driver holds at most max_shards rows besides one for each source, whose number is checked against `max_sources`.

Defined cases: null text has size 0 and gives nothing; a null source is a source of its own,
ordered last; a source without words has target 0; an empty table gives an empty result;
repeated rows each have their place on the tape; rows without an id are spread by their texts.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import chunks, cut, n_words, ship, text_buffer, word_spans


def targets(sizes: Sequence[float], weights: Sequence[float], cap: float = 3.0) -> list[float]:
    """Shares of sum(sizes) by weight, none above cap times its size; the excess goes to the others by weight."""
    total, out, free = float(sum(sizes)), [0.0] * len(sizes), set(range(len(sizes)))
    left = total
    while free:
        weight = sum(weights[i] for i in free)
        full = {i for i in free if left * weights[i] / weight > cap * sizes[i]}
        if not full:
            for i in free:
                out[i] = left * weights[i] / weight
            break
        for i in full:
            out[i] = cap * float(sizes[i])
        left -= sum(out[i] for i in full)
        free -= full
    return out


def sainte_lague(claims: Sequence[float], seats: int, most: Sequence[int] | None = None) -> list[int]:
    """Seats by highest quotients claim / (2k + 1), at most most[i] for i; ties to the smaller index.

    Rounding each exact share gives an allocation that some divisor yields; seats are then given
    to the highest next quotient, or taken from the lowest last one, until the total is met.
    """
    total = float(sum(claims))
    limit = [10**18] * len(claims) if most is None else list(most)
    if total <= 0 or seats <= 0:
        return [0] * len(claims)
    got = [min(limit[i], int(c * seats / total + 0.5)) for i, c in enumerate(claims)]
    short = min(seats, sum(x for x, c in zip(limit, claims, strict=True) if c > 0)) - sum(got)
    if short > 0:
        heap = [(-c / (2 * g + 1), i) for i, (c, g) in enumerate(zip(claims, got, strict=True)) if c > 0 and g < limit[i]]
        heapq.heapify(heap)
        while short and heap:
            _, i = heapq.heappop(heap)
            got[i] += 1
            short -= 1
            if got[i] < limit[i]:
                heapq.heappush(heap, (-claims[i] / (2 * got[i] + 1), i))
    elif short < 0:
        heap = [(c / (2 * g - 1), -i) for i, (c, g) in enumerate(zip(claims, got, strict=True)) if g]
        heapq.heapify(heap)
        while short:
            _, i = heapq.heappop(heap)
            got[-i] -= 1
            short += 1
            if got[-i]:
                heapq.heappush(heap, (claims[-i] / (2 * got[-i] - 1), i))
    return got


def in_words(want: int, block_words: int, room: Sequence[int], quota: Sequence[int]) -> list[int]:
    """Words of each shard: its quota of blocks, then a short block that brings the sum to `want`, to shards with room or from those with most."""
    out = [q * block_words for q in quota]
    gap = want - sum(out)
    for k in sorted(range(len(out)), key=lambda k: (out[k] - room[k], k) if gap > 0 else (-out[k], k)):
        step = min(gap, room[k] - out[k]) if gap > 0 else max(gap, -out[k])
        out[k] += step
        gap -= step
        if not gap:
            break
    return out


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), pa.array(n_words(b.column(3)))], names=["doc_id", "source", "body", "size"])


def document_sizes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """doc_id, source, body (hash of the text where the id is null, else 0), size."""
    ship(docs.sparkSession)
    text = F.col(text_col).cast("string")
    given = F.col(id_col).cast("long")
    rows = docs.select(given.alias("doc_id"), F.col(source_col).cast("string").alias("source"), F.when(given.isNull(), F.xxhash64(text)).otherwise(F.lit(0).cast("long")).alias("body"), text.alias("text"))
    return rows.mapInArrow(_count, "doc_id long, source string, body long, size long")


def mix(
    docs: DataFrame,
    weights: Sequence[float] = (5, 2, 1),
    id_col: str = "doc_id",
    text_col: str = "text",
    source_col: str = "source",
    seed: int = 11,
    block_words: int = 16,
    shard_words: int = 1 << 18,
    cap: float = 3.0,
    max_sources: int = 100_000,
    max_shards: int = 200_000,
) -> DataFrame:
    """doc_id, source, size, source_size, target, taken, first (words from the tape's seeded beginning taken once more), full (times the whole document is taken).

    Weights go to the sources in order of their UTF-8 bytes, repeating, null last. The words taken of a source are its target, rounded.
    """
    spark = docs.sparkSession
    sized = cut(document_sizes(docs, id_col, text_col, source_col))
    found = sized.groupBy("source").agg(F.sum("size").alias("words")).limit(max_sources + 1).collect()
    if len(found) > max_sources:
        raise ValueError(f"more than {max_sources} sources")
    found.sort(key=lambda r: (r.source is None, (r.source or "").encode()))
    sizes = [int(r.words or 0) for r in found]
    wants = targets(sizes, [weights[i % len(weights)] for i in range(len(found))], cap)
    blocks = sainte_lague(wants, round(sum(wants) / block_words), [int(cap * s) // block_words for s in sizes])
    per_shard = max(shard_words, -(-sum(sizes) // max_shards))
    shards = [max(1, -(-s // per_shard)) for s in sizes]
    of_source = spark.createDataFrame(
        [(i, r.source, s, float(t), n) for i, (r, s, t, n) in enumerate(zip(found, sizes, wants, shards, strict=True))],
        "src int, name string, source_size long, target double, n_shards int",
    )
    placed = (
        sized.join(of_source, F.col("source").eqNullSafe(F.col("name")))
        .withColumn("draw", F.xxhash64(F.lit(seed), "doc_id", "size", "body"))
        .withColumn("shard", F.pmod(F.xxhash64(F.lit(seed + 1), "doc_id", "body"), F.col("n_shards").cast("long")).cast("int"))
    )
    held = {(r.src, r.shard): int(r.words) for r in placed.groupBy("src", "shard").agg(F.sum("size").alias("words")).collect()}
    plan = []
    for i, n in enumerate(shards):
        own = [held.get((i, k), 0) for k in range(n)]
        room = [int(cap * w) for w in own]
        quota = sainte_lague(own, blocks[i], [r // block_words for r in room])
        for k, words in enumerate(in_words(min(sum(room), round(wants[i])), block_words, room, quota)):
            plan.append((i, k, *(divmod(words, own[k]) if own[k] else (0, 0))))
    quota = spark.createDataFrame(plan, "src int, shard int, full long, first long")
    tape = Window.partitionBy("src", "shard").orderBy("draw", "doc_id", "body").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    out = placed.withColumn("stop", F.sum("size").over(tape)).join(quota, ["src", "shard"])
    begin = F.col("stop") - F.col("size")
    more = F.greatest(F.lit(0), F.least(F.col("stop"), F.col("first")) - begin).cast("long")
    return out.select("doc_id", "source", "size", "source_size", "target", (F.col("full") * F.col("size") + more).cast("long").alias("taken"), more.alias("first"), "full")


def _first_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The texts (first column), cut behind the word whose number the second column has."""
    for b in batches:
        flat, off = text_buffer(b.column(0))
        want = b.column(1).to_numpy(zero_copy_only=False)
        stop = off[1:].copy()
        for i, j in chunks(off):
            a = off[i]
            _, end, doc = word_spans(flat[a : off[j]], off[i : j + 1] - a)
            first = np.searchsorted(doc, np.arange(j - i + 1))
            have = np.diff(first)
            short = np.flatnonzero(want[i:j] < have)
            stop[i + short] = np.where(want[i + short] > 0, a + end[first[:-1][short] + np.maximum(want[i + short], 1) - 1], off[:-1][i + short])
        raw = flat.tobytes()
        part = pa.array([raw[s:e].decode() for s, e in zip(off[:-1].tolist(), stop.tolist(), strict=True)], pa.string())
        yield pa.RecordBatch.from_arrays([*b.columns[:2], part, *b.columns[2:]], names=["__text", "__first", "__part", *b.schema.names[2:]])


def mixed_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", **options) -> DataFrame:
    """docs as often as the mix takes them, columns as they came.

    A document is repeated for every whole pass over it; the words that the mix takes once more
    from its beginning are a further row of the same id with the shorter text. Rows without an id share one plan.
    """
    plan = mix(docs, id_col=id_col, text_col=text_col, source_col=source_col, **options).where("taken > 0")
    plan = plan.groupBy("doc_id").agg(F.max("full").cast("int").alias("__full"), F.max("first").alias("__first")).withColumnRenamed("doc_id", "__id")
    taken = docs.join(plan, F.col(id_col).cast("long").eqNullSafe(F.col("__id")))
    shaped = taken.select(F.col(text_col).cast("string").alias("__text"), "__first", "__full", *(c for c in docs.columns if c != text_col))
    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in shaped.schema.fields[2:])
    cut_off = shaped.mapInArrow(_first_words, f"__text string, __first long, __part string, {kinds}")
    copies = F.concat(F.array_repeat("__text", F.col("__full")), F.when(F.col("__first") > 0, F.array("__part")).otherwise(F.array().cast("array<string>")))
    return cut_off.withColumn(text_col, F.explode(copies)).select(*docs.columns)
