"""Exact top-k inner-product search by distributed histogram selection.

Vectors are floored in generated code and written once; the table's row numbers tell rows that share an identifier apart.
Query rows are dealt to parts of a bounded number of bytes, candidate rows to lanes of a bounded number of
rows; a cell is one part and one lane. Its task holds the part's queries and streams the lane's candidates past them in Arrow
batches, scored as matrix products, so no row pair is ever materialised. Of the scores of a cell only those go on that
are among the k best of their query there (ties by identifier, then row): each of the others has k better ones and is in no answer.
They are written, and no vector is moved or scored a second time.

Scores are whole numbers. Each round counts, for every query, the scores of all cells in `bins` equal slices of the
interval that holds its k-th best (partial counts before the shuffle); the summed histograms pick the slice for the next round, until the
slice is one score wide. The scores from the k-th value on are kept, and of those equal to it the smallest identifiers.

Defined cases: vectors that are null, or hold a null or non-finite component, take no part; a
query row is not its own candidate, another row of the same identifier is; every query row has an answer of its own;
fewer than k candidates give all of them; vectors of different lengths are compared only within
a length; rows without an identifier take no part; an empty table gives an empty result. Scores are exact, or, if they could reach 2^62, an error.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, drop_cut, ship

#: Scores are below this.
_MOST = 1 << 62
#: Scores held at once by a task.
_GRID = 1 << 21


def _scores(q: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Exact integer products: as doubles while every partial sum is below 2^53, else as Python integers."""
    top = (np.abs(q).max(initial=0) * np.abs(c).max(initial=0)) * max(1, q.shape[1])
    if top < 2**53:
        return (q @ c.T).astype(np.int64)
    return (np.array([[int(x) for x in r] for r in q], object) @ np.array([[int(x) for x in r] for r in c], object).T).astype(np.int64)


class Best:
    """The k best candidates of each of a number of queries, among those met so far."""

    def __init__(self, ids: np.ndarray, rows: np.ndarray, vectors: np.ndarray, k: int):
        self.ids, self.rows, self.vectors, self.k = ids, rows, vectors, k
        self.least = np.full(len(ids), np.iinfo(np.int64).min)
        none = np.zeros(0, np.int64)
        self.held: tuple = (none, none, none, none)  # query, score, identifier, row
        self.open: list[tuple] = []
        self.n_open = 0

    def meet(self, ids: np.ndarray, rows: np.ndarray, vectors: np.ndarray) -> None:
        across = min(len(ids), 4096)
        step = max(1, _GRID // max(1, across))
        for j in range(0, len(ids), across):
            them = slice(j, j + across)
            for i in range(0, len(self.ids), step):
                us = slice(i, i + step)
                s = _scores(self.vectors[us], vectors[them])
                least = self.least[us]
                if s.shape[1] > self.k + 1 and (least == np.iinfo(np.int64).min).any():
                    # the k + 1 best of the batch hold k besides the query itself
                    least = np.maximum(least, np.partition(s, -(self.k + 1), axis=1)[:, -(self.k + 1)])
                q, c = np.nonzero(s >= least[:, None])
                other = self.rows[us][q] != rows[them][c]
                q, c = q[other], c[other]
                if len(q):
                    self.open.append((q + i, s[q, c], ids[them][c], rows[them][c]))
                    self.n_open += len(q)
                if self.n_open > _GRID:
                    self.fold()
            if self.n_open > 8 * self.k * len(self.ids) or (self.least == np.iinfo(np.int64).min).any():
                self.fold()

    def fold(self) -> None:
        q, s, ids, rows = (np.concatenate(x) for x in zip(self.held, *self.open, strict=True))
        order = np.lexsort((rows, ids, -s, q))
        place = np.arange(len(q)) - np.searchsorted(q[order], q[order], side="left")
        order, place = order[place < self.k], place[place < self.k]
        self.held, self.open, self.n_open = (q[order], s[order], ids[order], rows[order]), [], 0
        last = order[place == self.k - 1]
        self.least[q[last]] = s[last]

    def batches(self) -> Iterator[pa.RecordBatch]:
        self.fold()
        for i in range(0, len(self.held[0]), 1 << 16):
            q, s, ids, rows = (x[i : i + (1 << 16)] for x in self.held)
            yield pa.RecordBatch.from_arrays([pa.array(self.ids[q]), pa.array(self.rows[q]), pa.array(ids), pa.array(rows), pa.array(s)], names=["query_id", "query", "vec_id", "row", "score"])


def _by_length(lists: pa.Array, keep: np.ndarray) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(length, rows, matrix) of the chosen rows of a list column."""
    lists = lists.cast(pa.large_list(pa.float64()))
    off, flat = lists.offsets.to_numpy(), lists.values.to_numpy(zero_copy_only=False)
    length = np.diff(off)[keep]
    for dim in np.unique(length).tolist():
        rows = keep[length == dim]
        yield dim, rows, flat[off[rows][:, None] + np.arange(dim)]


def _survivors(k: int):
    """Rows sorted by cell, its queries first, to each query's k best in the cell."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, waiting, best = None, {}, {}

        def done() -> Iterator[pa.RecordBatch]:
            for found in best.values():
                yield from found.batches()

        for b in batches:
            cell, side, ids, rows = (b.column(b.schema.get_field_index(n)).to_numpy(zero_copy_only=False) for n in ("cell", "side", "id", "row"))
            edge = np.flatnonzero((cell[1:] != cell[:-1]) | (side[1:] != side[:-1])) + 1
            for start, stop in zip([0, *edge.tolist()], [*edge.tolist(), len(cell)], strict=True):
                if start == stop:
                    continue
                if cell[start] != at:
                    yield from done()
                    at, waiting, best = cell[start], {}, {}
                for dim, own, m in _by_length(b.column(b.schema.get_field_index("v")), np.arange(start, stop)):
                    if side[start] == 0:
                        waiting.setdefault(dim, []).append((ids[own], rows[own], m))
                        continue
                    if dim in waiting:
                        best[dim] = Best(*(np.concatenate(x) for x in zip(*waiting.pop(dim), strict=True)), k)
                    if dim in best:
                        best[dim].meet(ids[own], rows[own], m)
        yield from done()

    return run


def top_k(
    vectors: DataFrame,
    is_query: Column,
    k: int = 5,
    id_col: str = "vec_id",
    vector_col: str = "embedding",
    scale: float = 256.0,
    bins: int = 1024,
    part_bytes: int = 16 << 20,
    lane_rows: int = 1 << 20,
    lanes: int | None = None,
) -> DataFrame:
    """query_id, rank, vec_id, score: the k best candidates of each query row, ties to the smaller id."""
    spark = vectors.sparkSession
    ship(spark)
    v = F.col(vector_col)
    finite = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf")))
    whole = F.transform(v, lambda x: F.floor(F.lit(float(scale)) * x.cast("double")).cast("double"))
    rows = vectors.where(F.col(id_col).isNotNull() & v.isNotNull() & finite).select(F.col(id_col).cast("long").alias("id"), whole.alias("v"), F.coalesce(is_query, F.lit(False)).alias("asks"))
    held = cut(rows.withColumn("row", F.monotonically_increasing_id()))
    # Cauchy-Schwarz: no score lies outside the square of the longest vector
    square = F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x)
    seen = held.agg(F.count("*").alias("n"), F.max(square).alias("top"), F.sum(F.when(F.col("asks"), 8 * F.size("v") + 32)).alias("bytes")).first()
    if not seen["bytes"]:
        drop_cut(held)
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    if seen["top"] >= _MOST:
        raise ValueError("scores may reach 2^62; use a smaller scale")
    parts = -(-seen["bytes"] // part_bytes)
    lanes = lanes or max(-(-seen["n"] // lane_rows), -(-2 * spark.sparkContext.defaultParallelism // parts))
    dealt = lambda df, n, seed: F.pmod(F.xxhash64(df["row"], F.lit(seed)), F.lit(n)).cast("int")
    each = lambda n: F.explode(F.sequence(F.lit(0), F.lit(int(n) - 1)))
    asked = held.where("asks").withColumn("part", dealt(held, parts, 1)).withColumn("lane", each(lanes)).withColumn("side", F.lit(0))
    given = held.withColumn("lane", dealt(held, lanes, 2)).withColumn("part", each(parts)).withColumn("side", F.lit(1))
    cells = asked.unionByName(given).select((F.col("part") * F.lit(int(lanes)) + F.col("lane")).alias("cell"), "side", "id", "row", "v")
    met = cells.repartition(int(parts * lanes), "cell").sortWithinPartitions("cell", "side").mapInArrow(_survivors(k), "query_id long, query long, vec_id long, row long, score long")
    scored = cut(met)
    drop_cut(held)

    state = cut(scored.groupBy("query").agg(F.min("score").alias("low"), F.max("score").alias("high"), F.count("*").alias("n")))
    span = state.agg(F.max(F.col("high") - F.col("low") + 1)).first()[0]
    width = 1 if span is None else max(1, math.ceil(span / bins))
    while span is not None:
        at = F.least(F.expr(f"(score - low) div {width}L"), F.lit(bins)).cast("int")
        counts = scored.join(state, "query").where(F.col("score") >= F.col("low")).groupBy("query", at.alias("slice")).agg(F.count("*").alias("n"))
        above = Window.partitionBy("query").orderBy(F.desc("slice")).rowsBetween(Window.unboundedPreceding, Window.currentRow)
        found = counts.withColumn("upto", F.sum("n").over(above)).where(F.col("upto") >= k).groupBy("query").agg(F.max("slice").alias("slice"))
        # a query with fewer than k candidates keeps them all
        after = cut(state.select("query", "low").join(found, "query", "left").select("query", (F.col("low") + F.coalesce("slice", F.lit(0)).cast("long") * F.lit(width)).alias("low")))
        drop_cut(state)
        state = after
        if width == 1:
            break
        width = max(1, math.ceil(width / bins))
    best = scored.join(state.select("query", "low"), "query").where(F.col("score") >= F.col("low"))
    place = F.row_number().over(Window.partitionBy("query").orderBy(F.desc("score"), "vec_id", "row"))
    out = cut(best.withColumn("rank", place).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score"))
    drop_cut(scored)
    drop_cut(state)
    return out
