"""Drift detection on streams: windows, watermarks, keyed state, and retraining on drift."""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.chisq import chi2_sf, table_stat
from ..operators.detect import judge
from ..operators.histogram import Histogram
from ..session import ship

Windowing = tuple[str, ...]


def window_counts(stream: DataFrame, hist: Histogram, ts: str, window: Windowing, watermark: str = "1 hour", on_invalid: str = "drop") -> DataFrame:
    """(start, end, bin, n) of tumbling (one length) or sliding (length, step) windows; works on streams and on tables."""
    rows = hist.assign(stream.withColumn(ts, F.col(ts).cast("timestamp")), on_invalid=on_invalid)
    if stream.isStreaming:
        rows = rows.withWatermark(ts, watermark)
    return rows.groupBy(F.window(ts, *window).alias("w"), "bin").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "bin", "n")


def session_counts(stream: DataFrame, ts: str, key: str, gap: str, watermark: str = "1 hour") -> DataFrame:
    """(key, start, end, n) of sessions that end after a gap without rows."""
    rows = stream.withColumn(ts, F.col(ts).cast("timestamp"))
    if stream.isStreaming:
        rows = rows.withWatermark(ts, watermark)
    return rows.groupBy(F.session_window(ts, gap).alias("w"), key).agg(F.count("*").alias("n")).select(key, F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def judge_windows(counts: DataFrame, hist: Histogram, alpha: float = 0.05, min_rows: int = 1) -> DataFrame:
    """Test results of window counts (start, end, bin, n) against the stored training counts."""
    cells = [F.coalesce(F.sum(F.when(F.col("bin") == b, F.col("n"))), F.lit(0)).cast("long") for b in range(hist.n_bins)]
    wide = counts.groupBy("start", "end").agg(F.array(*cells).alias("t")).withColumn("o", F.array(*(F.lit(int(c)).cast("long") for c in hist.counts)))
    return judge(wide, alpha, keep=("start", "end")).where(F.col("n_test") >= min_rows)


def detect_stream(stream: DataFrame, hist: Histogram, ts: str, window: Windowing, sink: Callable[[DataFrame, int], None], checkpoint: str, watermark: str = "1 hour", alpha: float = 0.05, **trigger):
    """Starts a query that judges each closed window once and hands the results to sink(results, batch id)."""
    counts = window_counts(stream, hist, ts, window, watermark)

    def finish(batch: DataFrame, number: int) -> None:
        sink(judge_windows(batch, hist, alpha), number)

    # the windows of one length close together, so a batch holds all bins of a window
    return counts.writeStream.outputMode("append").option("checkpointLocation", checkpoint).foreachBatch(finish).trigger(**(trigger or {"availableNow": True})).start()


def run_to_memory(spark: SparkSession, df: DataFrame, name: str, checkpoint: str | None = None, mode: str = "append") -> DataFrame:
    """Runs a streaming frame over what is there and returns what it put out."""
    writer = df.writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True)
    query = (writer.option("checkpointLocation", checkpoint) if checkpoint else writer).start()
    query.awaitTermination()
    return spark.table(name)


def run_to_table(spark: SparkSession, df: DataFrame, path: str, checkpoint: str) -> DataFrame:
    """Runs a streaming frame over what is there into a Parquet sink and reads it back: nothing comes to the driver."""
    df.writeStream.outputMode("append").format("parquet").option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(df.schema).parquet(path)


def labels_within(stream: DataFrame, labels: DataFrame, key: str, ts: str, label_ts: str, delay: str, watermark: str = "1 hour") -> DataFrame:
    """Stream-stream join: each row with the labels of its key that arrive at most `delay` after it."""
    a = stream.withWatermark(ts, watermark).alias("a")
    b = labels.withWatermark(label_ts, watermark).alias("b")
    near = (F.col(f"b.{label_ts}") >= F.col(f"a.{ts}")) & (F.col(f"b.{label_ts}") <= F.col(f"a.{ts}") + F.expr(f"INTERVAL {delay}"))
    return a.join(b, (F.col(f"a.{key}") == F.col(f"b.{key}")) & near)


def once(stream: DataFrame, keys: Sequence[str], ts: str, watermark: str = "1 hour") -> DataFrame:
    """Each key once while the watermark remembers it."""
    return stream.withWatermark(ts, watermark).dropDuplicatesWithinWatermark(list(keys))


def late_rows(query) -> int:
    """Rows that a finished query's stateful operators dropped for being behind the watermark."""
    return sum(int(op.get("numRowsDroppedByWatermark", 0)) for p in query.recentProgress for op in p["stateOperators"])


def chunk_tests(stream: DataFrame, hist: Histogram, key: str, chunk: int, alpha: float = 0.05) -> DataFrame:
    """(key, chunk_no, n, stat, p_value, reject): every `chunk` rows of a key are one test set; open chunks are keyed state."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    ship(stream.sparkSession)
    bins, counts = hist.n_bins, [int(c) for c in hist.counts]
    placed = hist.assign(stream, on_invalid="drop").select(key, "bin")
    kind = stream.schema[key].dataType.simpleString()

    def step(k, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        number, held = (state.get[0], list(state.get[1])) if state.exists else (0, [0] * bins)
        out = []
        for f in frames:
            for b in f["bin"]:
                held[int(b)] += 1
                if sum(held) == chunk:
                    s, d = table_stat(counts, [held])
                    p = chi2_sf(float(s[0]), int(d[0]))
                    out.append((k[0], number, chunk, float(s[0]), p, p < alpha))
                    number, held = number + 1, [0] * bins
        state.update((number, held))
        yield pd.DataFrame(out, columns=[key, "chunk_no", "n", "stat", "p_value", "reject"])

    return placed.groupBy(key).applyInPandasWithState(step, f"{key} {kind}, chunk_no int, n int, stat double, p_value double, reject boolean", "number int, held array<long>", "append", GroupStateTimeout.NoTimeout)


def adapt_loop(batches: Sequence[tuple], fit_detector: Callable, fit_learner: Callable, accuracy: Callable, is_drift: Callable, policy: str = "retrain") -> list[dict]:
    """Accuracy per batch of a learner that is refitted 'retrain' (on drift), 'none' (never) or 'always'.

    batches: items that the callables understand; the first trains both learner and detector.
    """
    if policy not in ("retrain", "none", "always"):
        raise ValueError("policy is 'retrain', 'none' or 'always'")
    detector, learner = fit_detector(batches[0]), fit_learner(batches[0])
    out = []
    for no, batch in enumerate(batches[1:], 1):
        drift = bool(is_drift(detector, batch))
        out.append({"batch": no, "drift": drift, "accuracy": float(accuracy(learner, batch)), "policy": policy})
        if policy == "always" or (policy == "retrain" and drift):
            detector, learner = fit_detector(batch), fit_learner(batch)
    return out
