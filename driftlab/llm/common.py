"""Shared plumbing of the training-data operators.

Texts reach Python as Arrow batches and are worked on as one flat byte buffer with
document offsets, cut into chunks of a bounded number of bytes, so a task's memory
depends on the chunk size and its longest single document, not on the table.
"""

from __future__ import annotations

import ctypes
import hashlib
import re
import tempfile
import uuid
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import ship

#: Bytes of text worked on at once inside a task.
CHUNK_BYTES = 1 << 20

_U = np.uint64
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True


def _lean() -> None:
    """Large buffers are mapped, and go back to the system when they are freed: Python workers live long beside an executor's heap."""
    pa.set_memory_pool(pa.system_memory_pool())
    try:
        libc = ctypes.CDLL("libc.so.6")
        libc.mallopt(-3, 4 << 20)  # M_MMAP_THRESHOLD, which else grows with use
        libc.mallopt(-1, 16 << 20)  # M_TRIM_THRESHOLD
    except (OSError, AttributeError):
        pass  # not glibc


_lean()


def checkpoint_dir(spark: SparkSession) -> str:
    """The shared folder for cut lineage: the session's own, or a local one where none is set and all runs in one process (tests)."""
    sc = spark.sparkContext
    found = spark.conf.get("spark.checkpoint.dir", None)
    held = sc._jsc.sc().getCheckpointDir()
    if held.isDefined():
        return found or held.get()
    if not found:
        if not re.fullmatch(r"local(\[[^,]*(,\s*\d+)?\])?", sc.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        found = tempfile.mkdtemp(prefix="driftlab-checkpoint-")
    sc.setCheckpointDir(found)
    return found


#: Folders that cut() has written and nothing has deleted yet, in order.
_CUTS: list[str] = []


def cut(df: DataFrame) -> DataFrame:
    """Write df to the shared folder as Parquet and read it back: no lineage behind it, and column pruning ahead."""
    spark = df.sparkSession
    path = f"{checkpoint_dir(spark)}/driftlab-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _CUTS.append(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._driftlab_cut = path
    return out


def _delete(spark: SparkSession, path: str) -> None:
    folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(folder, True)
    if path in _CUTS:
        _CUTS.remove(path)


def drop_cut(df: DataFrame) -> None:
    """Delete what cut() wrote for df; call it when no later step reads it again."""
    path = getattr(df, "_driftlab_cut", None)
    if path:
        _delete(df.sparkSession, path)


def clear_cuts(spark: SparkSession, since: int = 0, keep: Sequence[DataFrame] = ()) -> None:
    """Delete what cut() has written from number `since` (of cuts_made) on, but for `keep`.

    An operator's result may still read its cuts: call this once the result has been written.
    """
    held = {getattr(df, "_driftlab_cut", None) for df in keep}
    for path in [p for p in _CUTS[since:] if p not in held]:
        _delete(spark, path)


def cuts_made() -> int:
    return len(_CUTS)


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_buffer(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string column as one buffer, and int64 offsets (rows + 1); null is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if not pa.types.is_large_string(column.type):
        column = column.cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    if len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, off, data = column.buffers()
    offsets = np.frombuffer(off, np.int64, len(column) + 1, column.offset * 8)
    flat = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return flat[offsets[0] : offsets[-1]], offsets - offsets[0]


def chunks(offsets: np.ndarray, limit: int = CHUNK_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of documents of at most `limit` bytes together, a longer document alone."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = int(np.searchsorted(offsets, offsets[i] + limit, side="right")) - 1
        j = min(n, max(j, i + 1))
        yield i, j
        i = j


def mix64(x: np.ndarray) -> np.ndarray:
    """Bijective 64-bit scrambler (xor-shift, multiply)."""
    x = np.asarray(x, dtype=_U)
    x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


def _lane(seed: int) -> tuple[int, np.ndarray]:
    table = mix64(np.arange(256, dtype=_U) + _U(seed * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF))
    return int(mix64(np.array([seed + 77], _U))[0]) | 5, table


_LANES = {k: _lane(k) for k in (1, 2)}
_POWERS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def powers(lane: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """B^0..B^(n-1) and the inverse powers, modulo 2^64."""
    held = _POWERS.get(lane)
    if held is None or len(held[0]) < n:
        size = 1 << max(16, int(n).bit_length())
        base = _LANES[lane][0]
        inverse = pow(base, -1, 1 << 64)
        with np.errstate(over="ignore"):
            up = np.full(size, base, _U)
            up[0] = 1
            down = np.full(size, inverse, _U)
            down[0] = 1
            held = (np.cumprod(up), np.cumprod(down))
        _POWERS[lane] = held
    return held[0][:n], held[1][:n]


class SpanHash:
    """Position-free 64-bit hashes of any spans of a sequence of 64-bit values.

    Fast, for choosing candidates: long spans of equal hash can be constructed, so nothing is decided by it alone.
    """

    def __init__(self, values: np.ndarray, lane: int):
        up, self.down = powers(lane, len(values) + 1)
        self.sums = np.zeros(len(values) + 1, _U)
        with np.errstate(over="ignore"):
            np.cumsum(values * up[: len(values)], out=self.sums[1:])

    def of(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            raw = (self.sums[end] - self.sums[start]) * self.down[start]
            return mix64(raw ^ ((end - start).astype(_U) * _U(0xD6E8FEB86659FD93)))


def byte_hash(flat: np.ndarray, lane: int) -> SpanHash:
    return SpanHash(_LANES[lane][1][flat], lane)


def token_names(flat: np.ndarray, start: np.ndarray, end: np.ndarray, long: int = 64) -> np.ndarray:
    """64-bit names of byte spans that stand for their content: spans of over `long` bytes by a BLAKE2 digest."""
    out = byte_hash(flat, 1).of(start, end)
    for i in np.flatnonzero(end - start > long).tolist():
        out[i] = int.from_bytes(hashlib.blake2b(flat[start[i] : end[i]].tobytes(), digest_size=8).digest(), "little")
    return out


def word_spans(flat: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, end (bytes) and document number of each word, a word being a run without the six ASCII blanks."""
    solid = ~_SPACE[flat]
    first, last = solid.copy(), solid.copy()
    if len(flat):
        first[1:] &= ~solid[:-1]
        last[:-1] &= ~solid[1:]
        edge = offsets[:-1][offsets[:-1] < offsets[1:]]
        first[edge] = solid[edge]
        edge = offsets[1:][offsets[:-1] < offsets[1:]] - 1
        last[edge] = solid[edge]
    start = np.flatnonzero(first)
    end = np.flatnonzero(last) + 1
    return start, end, np.searchsorted(offsets, start, side="right") - 1


def n_words(column: pa.Array) -> np.ndarray:
    """Words of each text of an Arrow column."""
    flat, offsets = text_buffer(column)
    out = np.zeros(len(offsets) - 1, np.int64)
    for i, j in chunks(offsets):
        a = offsets[i]
        _, _, doc = word_spans(flat[a : offsets[j]], offsets[i : j + 1] - a)
        out[i:j] = np.bincount(doc, minlength=j - i)
    return out


def signed(x: np.ndarray) -> np.ndarray:
    return np.ascontiguousarray(x).view(np.int64)


def as_text(df: DataFrame, text: str = "text") -> DataFrame:
    """df with null texts made empty."""
    return df.withColumn(text, F.coalesce(F.col(text).cast("string"), F.lit("")))


#: Ids are below this; from here on stand the numbers given to rows without an id.
NO_ID = 1 << 62


def stand_in(id_col: str, text_col: str) -> Column:
    """The id, or for a null id a number from NO_ID on that hashes the text; an id of its own from NO_ID on is an error."""
    given = F.col(id_col).cast("long")
    own = F.lit(NO_ID) + F.pmod(F.conv(F.substring(F.sha2(F.coalesce(F.col(text_col).cast("string"), F.lit("")), 256), 1, 15), 16, 10).cast("long"), F.lit(NO_ID))
    return F.when(given >= NO_ID, F.raise_error(F.lit("identifiers must be below 2^62")).cast("long")).otherwise(F.coalesce(given, own)).alias("doc_id")


def min_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, component) for every node of an undirected edge list (a, b): the smallest node reachable.

    Alternating large-star and small-star rounds; each round's edges are cut to the shared
    folder, and a round that changes nothing ends it. Edges only, nothing comes to the driver
    but a count and a checksum of each round.
    """

    def neighbours(e: DataFrame) -> DataFrame:
        return e.select("a", "b").union(e.select(F.col("b").alias("a"), F.col("a").alias("b")))

    def star(pairs: DataFrame, keep) -> DataFrame:
        low = pairs.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        out = pairs.join(low, "a").where(keep).select(F.col("b").alias("a"), F.col("m").alias("b"))
        return out

    def mark(e: DataFrame):
        return e.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(20,0)"))).first()

    edges = cut(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct())
    before = tuple(mark(edges))
    for _ in range(max_rounds):
        large = star(neighbours(edges), F.col("b") > F.col("a")).where("a <> b")
        small_in = large.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
        low = small_in.groupBy("a").agg(F.min("b").alias("m"))
        small = small_in.join(low, "a").select(F.explode(F.array(F.struct(F.col("b").alias("a"), F.col("m").alias("b")), F.struct("a", F.col("m").alias("b")))).alias("e")).select("e.a", "e.b").where("a <> b").distinct()
        new = cut(small)
        drop_cut(edges)
        edges, now = new, tuple(mark(new))
        if now == before:
            break
        before = now
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return edges.select(F.col("a").alias("node"), F.col("b").alias("component"))
