"""Exact deduplication: Patricia tries own each distinct text.

Each map task folds the texts of a bounded chunk into a trie first, and texts that repeat in a chunk
stay with the task (up to `HELD_BYTES` of them) and leave it once at its end, so a text that a third of
all rows share leaves a task once, not once per row or chunk. What remains is dealt out by
(byte length, content hash) and sorted by it; a task then inserts the full byte strings into
tries whose terminal nodes keep the owner (smallest or largest identifier) and the number of
rows. All texts of one (length, hash) stand below one subtree, and the sorted order completes
subtrees one after another: a finished subtree is flushed to the output and dropped, so a task
holds one subtree and one Arrow batch however large the partition is. Rows find their owner by
SHA-256; the tries compare whole texts, and two different texts under one digest raise an error.

Defined cases: null text counts as empty; empty texts are equal to each other; null identifiers
take part as copies but never own a group that has a non-null identifier; an empty table gives
an empty result; extra columns are not touched.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import as_text, chunks, ship, text_buffer


class PatriciaTrie:
    """Compressed radix trie over byte strings. A node is [label, children, terminal value or None]."""

    def __init__(self, pick) -> None:
        self.root: list = [b"", {}, None]
        self.pick = pick

    def add(self, key: bytes, owner: int | None, rows: int = 1) -> None:
        node, at = self.root, 0
        while at < len(key):
            child = node[1].get(key[at])
            if child is None:
                node[1][key[at]] = [key[at:], {}, (owner, rows)]
                return
            label = child[0]
            if key.startswith(label, at):
                node, at = child, at + len(label)
                continue
            k = self._common(label, key, at)
            lower = [label[k:], child[1], child[2]]
            child[0], child[1], child[2] = label[:k], {label[k]: lower}, None
            node, at = child, at + k
        held = node[2]
        if held is None:
            node[2] = (owner, rows)
        else:
            owners = [x for x in (held[0], owner) if x is not None]
            node[2] = (self.pick(owners) if owners else None, held[1] + rows)

    @staticmethod
    def _common(label: bytes, key: bytes, at: int) -> int:
        """Length of the common prefix, by halving."""
        lo, hi = 1, min(len(label), len(key) - at)
        while lo < hi:
            mid = (lo + hi + 1) // 2
            if label[:mid] == key[at : at + mid]:
                lo = mid
            else:
                hi = mid - 1
        return lo

    def items(self) -> Iterator[tuple[bytes, int | None, int]]:
        """(byte string, owner, rows) of every terminal node, without recursion."""
        stack = [(self.root, b"")]
        while stack:
            node, above = stack.pop()
            path = above + node[0]
            if node[2] is not None:
                yield path, *node[2]
            stack.extend((child, path) for child in node[1].values())


#: Bytes of repeated texts that a map task keeps to its end.
HELD_BYTES = 16 << 20


def _fold(pick, id_col: int, text_col: int):
    """Map side: distinct texts of each chunk, with owner and row count; repeated ones once per task."""

    def batch_of(found: list) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays(
            [
                pa.array([len(t) for t, _, _ in found], pa.int64()),
                pa.array(np.array([xxhash.xxh3_64_intdigest(t) for t, _, _ in found], np.uint64).view(np.int64)),
                pa.array([t for t, _, _ in found], pa.binary()),
                pa.array([o for _, o, _ in found], pa.int64()),
                pa.array([n for _, _, n in found], pa.int64()),
            ],
            names=["n_bytes", "content", "body", "owner", "n_rows"],
        )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[bytes, tuple] = {}
        room = HELD_BYTES
        for batch in batches:
            ids = batch.column(id_col).to_pylist()
            flat, offsets = text_buffer(batch.column(text_col))
            raw = flat.tobytes()
            for i, j in chunks(offsets, 8 << 20):
                trie = PatriciaTrie(pick)
                for d in range(i, j):
                    trie.add(raw[offsets[d] : offsets[d + 1]], ids[d])
                found = []
                for text, owner, rows in trie.items():
                    old = held.get(text)
                    if old is not None:
                        owners = [x for x in (old[0], owner) if x is not None]
                        held[text] = (pick(owners) if owners else None, old[1] + rows)
                    elif rows > 1 and len(text) + 200 <= room:
                        room -= len(text) + 200
                        held[text] = (owner, rows)
                    else:
                        found.append((text, owner, rows))
                yield batch_of(found)
        for i in range(0, len(held), 1000):
            yield batch_of([(t, *held[t]) for t in list(held)[i : i + 1000]])

    return run


def _own(pick):
    """Reduce side: one subtree of (length, hash) at a time."""

    def flush(trie: PatriciaTrie, out: list) -> None:
        for text, owner, rows in trie.items():
            out.append((hashlib.sha256(text).hexdigest(), owner, rows))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trie, at, out = PatriciaTrie(pick), None, []
        for batch in batches:
            for n, h, body, owner, rows in zip(*(batch.column(k).to_pylist() for k in range(5)), strict=True):
                if at != (n, h):
                    flush(trie, out)
                    trie, at = PatriciaTrie(pick), (n, h)
                trie.add(body, owner, rows)
            if out:
                yield _owners(out)
                out = []
        if at is not None:
            flush(trie, out)
        if out:
            yield _owners(out)

    return run


def _owners(rows: list) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.string()), pa.array([r[1] for r in rows], pa.int64()), pa.array([r[2] for r in rows], pa.int64())], names=["digest", "keep_id", "group_size"])


def text_owners(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "min") -> DataFrame:
    """(digest, keep_id, group_size): one row per distinct text."""
    ship(docs.sparkSession)
    pick = {"min": min, "max": max}[keep]
    local = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text")).mapInArrow(_fold(pick, 0, 1), "n_bytes long, content long, body binary, owner long, n_rows long")
    dealt = local.repartition("n_bytes", "content").sortWithinPartitions("n_bytes", "content")
    return dealt.mapInArrow(_own(pick), "digest string, keep_id long, group_size long")


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "min") -> DataFrame:
    """One row per document: id, keep_id, group_size, kept, text_sha256; null ids stay with their group.

    kept is true for the row whose id is the owner's (every row of it, where rows repeat whole).
    The join by digest has few bytes per row; a digest that a large share of the rows has is
    split by Spark's adaptive skew join.
    """
    owners = text_owners(docs, id_col, text_col, keep)
    rows = as_text(docs, text_col).select(F.col(id_col).cast("long").alias(id_col), F.sha2(F.col(text_col), 256).alias("text_sha256"))
    joined = rows.join(owners, rows.text_sha256 == owners.digest)
    return joined.select(id_col, "keep_id", "group_size", F.col(id_col).eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256")


def drop_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "min") -> DataFrame:
    """docs without the rows that are not their text's owner; columns as they came. Of rows repeated whole, one stays."""
    owners = text_owners(docs, id_col, text_col, keep).select(F.col("keep_id").alias("__keep"), F.col("digest").alias("__owned"))
    rows = docs.withColumn("__digest", F.sha2(F.coalesce(F.col(text_col).cast("string"), F.lit("")), 256))
    kept = rows.join(owners, (F.col("__digest") == F.col("__owned")) & F.col(id_col).eqNullSafe(F.col("__keep")), "left_semi")
    return kept.dropDuplicates([id_col, "__digest"]).drop("__digest")
