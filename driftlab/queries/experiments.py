"""Queries of the experiments, of streams, of adaptation, and of the pipeline and SQL surfaces."""

from __future__ import annotations

import uuid

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.chisq import sf_sql
from ..functions.sqlfuncs import register_all
from ..operators import fitting, measures
from ..operators.histogram import fixed_histogram, load, save
from ..operators.ml import BalancedBins
from ..plans import workloads
from ..plans.harness import METHODS
from ..session import shared_folder
from ..sources.gen import DriftSource
from ..sources.tables import letter_shares, standard_rows, stratified, table
from ..streaming import monitor
from . import query


def _shared(spark, name: str) -> str:
    return f"{shared_folder(spark)}/driftlab-{name}-{uuid.uuid4().hex}"


def _errors(trials: DataFrame) -> DataFrame:
    got = measures.error_flags(trials)
    return got.select("workload", "method", F.round("type1", 4).alias("type1"), F.round("type2", 4).alias("type2"), "over_alpha", "best")


# ------------------------------------------------------------------ experiments (judged by bands in tests)


def _lines(spark, d):
    """Rows of lineitem for the two-dimensional experiments: price and quantity, moments of the whole table."""
    li = table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_extendedprice", "l_quantity")
    return standard_rows(li, ("l_extendedprice", "l_quantity"), ("l_orderkey", "l_linenumber", "l_partkey"), _shared(spark, "lines"))


@query()
def exp1_partition(spark, d):
    """How even the bins are, for both centroid methods on three shapes made of 1 350 rows of lineitem."""
    return workloads.partition_experiment(spark, source=_lines(spark, d))


@query()
def exp2_type1_type2(spark, d):
    """Errors of six methods on six two-dimensional workloads, rows of lineitem with and without drift, by a reduced protocol: 2 runs of 15 + 15 sets."""
    return _errors(workloads.two_dimensional(spark, runs=2, tests=15, source=_lines(spark, d)))


@query()
def exp2_ranks(spark, d):
    return measures.error_rank(workloads.two_dimensional(spark, runs=2, tests=15, methods=("balanced", "plain_kmeans", "midpoint_kd", "peel_chi2", "peel_tv"), source=_lines(spark, d)))


@query()
def exp2_train_size(spark, d):
    """Four training sizes on two of the six workloads, by a reduced protocol: 1 run of 15 + 15 sets (run_experiments takes all six), on rows of lineitem."""
    return _errors(workloads.training_sizes(spark, runs=1, tests=15, source=_lines(spark, d)))


@query()
def exp3_dims(spark, d):
    """Histogram methods in 4, 8 and 20 dimensions, by a reduced protocol: 1 run of 8 + 8 sets (run_experiments takes all five dimensions).

    The dimensions are the first components of `embeddings`, in all vectors without null or non-finite components; its rows repeat in the sets where they are fewer than 7 200.
    """
    sound = F.forall("embedding", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf")))
    e = table(spark, d, "embeddings").where(F.col("embedding").isNotNull() & (F.size("embedding") >= 20) & sound)
    vectors = e.select("vec_id", *(F.col("embedding")[j].cast("double").alias(f"e{j}") for j in range(20)))
    source = standard_rows(vectors, [f"e{j}" for j in range(20)], ("vec_id",), _shared(spark, "vectors"))
    return _errors(workloads.dimensions(spark, dims=(4, 8, 20), runs=1, tests=8, methods=METHODS[:-1], source=source))


@query()
def compare_methods(spark, d):
    """Every year of lineitem judged by five methods fitted to 4 000 rows of the years before 1997 and counted on all of them: a control without drift.

    The runs test is left out: whole years are beyond its quadratic cap.
    """
    from ..plans.harness import compare
    from .drift import KEYS, rows_of

    p = rows_of(spark, d)
    got = compare(("balanced", "plain_kmeans", "midpoint_kd", "peel_chi2", "peel_tv"), p.where("yr < 1997"), p.where("yr >= 1997"), ("x", "y"), "yr", sample_cap=4000, keys=KEYS)
    return got.select("method", "yr", F.round("stat", 6).alias("stat"), F.round("p_value", 6).alias("p_value"), "reject")


def _exp4(which: str):
    def run(spark, d):
        return _errors(workloads.document_experiment(spark, d, which, runs=1, tests=8))

    run.__name__ = f"exp4_{which}"
    run.__doc__ = f"Errors of six methods on document workload {which}."
    return query()(run)


for _w in workloads.SIZES:
    _exp4(_w)


# ------------------------------------------------------------------ streams

_CENTRES = ((0.3, 0.25), (0.3, 0.75), (1.2, 0.5))
_E = "(SELECT *, value / 100 AS x, hour(ts) / 24.0 AS y FROM events)"
_d = [f"((x - {a}) * (x - {a}) + (y - {b}) * (y - {b}))" for a, b in _CENTRES]
_BIN = f"(CASE WHEN {_d[0]} <= {_d[1]} AND {_d[0]} <= {_d[2]} THEN 0 WHEN {_d[1]} <= {_d[2]} THEN 1 ELSE 2 END)"
_CLOSED = "(SELECT max(ts) - INTERVAL 1 HOUR AS mark FROM events)"
_US = lambda c: f"epoch_us({c})"


def _features(events: DataFrame) -> DataFrame:
    return events.select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"), (F.col("value") / 100).alias("x"), (F.hour("ts") / 24.0).alias("y"))


def _stream(spark, d) -> DataFrame:
    path = f"{d}/events.parquet"
    schema = spark.read.parquet(path).schema
    # a glob, so that a single file is a stream too
    return _features(spark.readStream.schema(schema).parquet(f"{d}/events*.parquet"))


def _hist(counts=None):
    return fixed_histogram(("x", "y"), _CENTRES, counts=counts)


def _counts(spark, d) -> np.ndarray:
    got = {r.bin: r.n for r in _hist().assign(_features(table(spark, d, "events"))).groupBy("bin").agg(F.count("*").alias("n")).collect()}
    return np.array([got.get(k, 0) for k in range(3)])


def _micros(df: DataFrame) -> DataFrame:
    return df.withColumn("start", F.unix_micros("start")).withColumn("end", F.unix_micros("end"))


@query(f"""WITH w AS (SELECT date_trunc('day', ts) AS day, {_BIN} AS bin, count(*) AS n FROM {_E} GROUP BY 1, 2)
           SELECT {_US('day')} AS start, {_US("day + INTERVAL 1 DAY")} AS "end", bin, n FROM w, {_CLOSED} WHERE day + INTERVAL 1 DAY <= mark""")
def stream_window_counts(spark, d):
    """Daily counts per bin of the windows that the watermark has closed."""
    got = monitor.window_counts(_stream(spark, d), _hist(), "ts", ("1 day",))
    return _micros(monitor.run_to_memory(spark, got, f"w_{uuid.uuid4().hex}", _shared(spark, "w")))


@query(f"""WITH s AS (SELECT date_trunc('day', ts) - to_days(k::INTEGER) AS day, {_BIN} AS bin FROM {_E}, range(2) r(k)), w AS (SELECT day, bin, count(*) AS n FROM s GROUP BY 1, 2)
           SELECT {_US('day')} AS start, {_US("day + INTERVAL 2 DAY")} AS "end", bin, n FROM w, {_CLOSED} WHERE day + INTERVAL 2 DAY <= mark""")
def stream_slide_counts(spark, d):
    got = monitor.window_counts(_stream(spark, d), _hist(), "ts", ("2 days", "1 day"))
    return _micros(monitor.run_to_memory(spark, got, f"s_{uuid.uuid4().hex}", _shared(spark, "s")))


@query(f"""WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
           n AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM g),
           a AS (SELECT user_id, min(ts) AS first, max(ts) + INTERVAL 30 MINUTE AS stop, count(*) AS n FROM n GROUP BY user_id, s)
           SELECT user_id, {_US('first')} AS start, {_US('stop')} AS "end", n FROM a, {_CLOSED} WHERE stop <= mark""")
def stream_session(spark, d):
    got = monitor.session_counts(_stream(spark, d), "ts", "user_id", "30 minutes")
    return _micros(monitor.run_to_table(spark, got, _shared(spark, "g"), _shared(spark, "g-state")))


_DAYS = f"""WITH t AS (SELECT date_trunc('day', ts) AS day, count(*) FILTER (WHERE {_BIN} = 0) AS t0, count(*) FILTER (WHERE {_BIN} = 1) AS t1, count(*) FILTER (WHERE {_BIN} = 2) AS t2 FROM {_E} GROUP BY 1),
    o AS (SELECT sum(t0)::DOUBLE AS o0, sum(t1)::DOUBLE AS o1, sum(t2)::DOUBLE AS o2 FROM t), m AS (SELECT *, o0 + o1 + o2 AS n, (t0 + t1 + t2)::DOUBLE AS q FROM t, o, {_CLOSED} WHERE day + INTERVAL 1 DAY <= mark),
    r AS (SELECT day, q, ({" + ".join(f"(q * o{k} - n * t{k}) * (q * o{k} - n * t{k}) / (o{k} + t{k})" for k in range(3))}) / (n * q) AS stat FROM m)"""


@query(f"{_DAYS} SELECT {_US('day')} AS start, round(stat, 6) AS stat, round({sf_sql('stat', '2')}, 6) AS p_value, {sf_sql('stat', '2')} < 0.05 AS reject, q::BIGINT AS n_test FROM r")
def stream_detect(spark, d):
    """Every closed day of the stream against the stored counts, judged in foreachBatch."""
    out = _shared(spark, "detect")
    q = monitor.detect_stream(_stream(spark, d), _hist(_counts(spark, d)), "ts", ("1 day",), lambda df, _: df.write.mode("append").parquet(out), _shared(spark, "detect-state"))
    q.awaitTermination()
    got = spark.read.parquet(out)
    return got.select(F.unix_micros("start").alias("start"), F.round("stat", 6).alias("stat"), F.round("p_value", 6).alias("p_value"), "reject", "n_test")


@query("""SELECT count(DISTINCT date_trunc('day', ts))::BIGINT AS dropped FROM (SELECT TIMESTAMP '2024-01-26 12:00:00' AS ts FROM range(20))
          WHERE date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR""")
def stream_late(spark, d):
    """Rows that come three days late are dropped; the operator counts them behind its partial counts, so rows of one window and bin count once."""
    src = _shared(spark, "late-in")
    events = _features(table(spark, d, "events")).withColumn("ts", F.col("ts").cast("timestamp"))
    events.coalesce(1).write.mode("append").parquet(src)
    late = spark.range(20).select(F.col("id").alias("event_id"), F.lit(0).cast("long").alias("user_id"), F.lit("2024-01-26 12:00:00").cast("timestamp").alias("ts"), F.lit(0.5).alias("x"), F.lit(0.5).alias("y"))
    schema = spark.read.parquet(src).schema
    state, name = _shared(spark, "late-state"), f"l_{uuid.uuid4().hex}"

    def go():
        stream = spark.readStream.schema(schema).parquet(src)
        counts = monitor.window_counts(stream, _hist(), "ts", ("1 day",))
        q = counts.writeStream.outputMode("append").format("noop").queryName(name).option("checkpointLocation", state).trigger(availableNow=True).start()
        q.awaitTermination()
        return q

    go()
    late.coalesce(1).write.mode("append").parquet(src)
    # the second run goes on from the checkpoint, watermark included
    return spark.createDataFrame([(monitor.late_rows(go()),)], "dropped long")


@query(f"SELECT user_id, (count(*) // 10)::BIGINT AS chunks FROM {_E} GROUP BY 1 HAVING count(*) >= 10")
def stream_chunks(spark, d):
    """Every ten rows of a user are a test set; open chunks are keyed state."""
    got = monitor.chunk_tests(_stream(spark, d), _hist(_counts(spark, d)), "user_id", 10)
    done = monitor.run_to_memory(spark, got, f"c_{uuid.uuid4().hex}", _shared(spark, "c"))
    return done.groupBy("user_id").agg(F.count("*").alias("chunks"))


@query(f"""WITH t AS (SELECT date_trunc('day', ts) AS day, count(*) AS n FROM events GROUP BY 1) SELECT {_US('day')} AS start, n FROM t""")
def batch_window_counts(spark, d):
    """The same windows on the table as a batch, all of them."""
    got = monitor.window_counts(_features(table(spark, d, "events")), _hist(), "ts", ("1 day",))
    return got.groupBy(F.unix_micros("start").alias("start")).agg(F.sum("n").alias("n"))


@query("SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")
def stream_static_join(spark, d):
    """Each event of the stream with its customer's segment, into a Parquet sink."""
    c = table(spark, d, "customer").select("c_custkey", "c_mktsegment")
    got = _stream(spark, d).join(c, F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment")
    return monitor.run_to_table(spark, got, _shared(spark, "static"), _shared(spark, "static-state"))


@query("SELECT a.event_id, b.event_id AS label_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id % 2 = 0 AND b.event_id % 2 = 1 AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 2 HOUR")
def stream_stream_join(spark, d):
    """Even events with the odd events of the same user in the two hours after them, as late labels."""
    a = _stream(spark, d).where("event_id % 2 = 0").select("event_id", "user_id", "ts")
    b = _stream(spark, d).where("event_id % 2 = 1").select(F.col("event_id").alias("label_id"), "user_id", F.col("ts").alias("label_ts"))
    got = monitor.labels_within(a, b, "user_id", "ts", "label_ts", "2 hours").select("event_id", "label_id")
    return monitor.run_to_table(spark, got, _shared(spark, "pairs"), _shared(spark, "pairs-state"))


@query("SELECT event_id, 1 AS n FROM events")
def stream_dedup(spark, d):
    """The stream twice over, each event once."""
    s = _stream(spark, d).select("event_id", "ts")
    got = monitor.run_to_table(spark, monitor.once(s.union(_stream(spark, d).select("event_id", "ts")), ["event_id"], "ts").select("event_id"), _shared(spark, "once"), _shared(spark, "once-state"))
    return got.groupBy("event_id").agg(F.count("*").cast("int").alias("n"))


_E15 = "(SELECT *, value * CASE WHEN ts >= TIMESTAMP '2024-01-15' THEN 1.5 ELSE 1.0 END / 100 AS x, hour(ts) / 24.0 AS y FROM events)"
_DRIFT = _DAYS.replace(_E, _E15).replace("FROM t), m AS", "FROM t WHERE day < TIMESTAMP '2024-01-15'), m AS")


@query(f"{_DRIFT} SELECT {_US('day')} AS start, round(stat, 6) AS stat, {sf_sql('stat', '2')} < 0.05 AS reject, q::BIGINT AS n_test FROM r")
def stream_drift(spark, d):
    """Values grow by half from day 15 on: every closed day against the days before."""
    late = F.col("ts") >= F.lit("2024-01-15").cast("timestamp")
    moved = lambda df: df.withColumn("x", F.col("x") * F.when(late, 1.5).otherwise(1.0))
    before = {r.bin: r.n for r in _hist().assign(moved(_features(table(spark, d, "events"))).where(~late)).groupBy("bin").agg(F.count("*").alias("n")).collect()}
    out = _shared(spark, "drift")
    hist = _hist(np.array([before.get(k, 0) for k in range(3)]))
    monitor.detect_stream(moved(_stream(spark, d)), hist, "ts", ("1 day",), lambda df, _: df.write.mode("append").parquet(out), _shared(spark, "drift-state")).awaitTermination()
    return spark.read.parquet(out).select(F.unix_micros("start").alias("start"), F.round("stat", 6).alias("stat"), "reject", "n_test")


# ------------------------------------------------------------------ adaptation


def _logistic(x: np.ndarray, y: np.ndarray, rounds: int = 300) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    mean, sd = x.mean(axis=0), x.std(axis=0) + 1e-9
    z = np.c_[(x - mean) / sd, np.ones(len(x))]
    w = np.zeros(z.shape[1])
    for _ in range(rounds):
        w -= 0.5 * (z.T @ (1 / (1 + np.exp(-z @ w)) - y) / len(z) + 1e-3 * w)
    return w, mean, sd


@query()
def adapt_accuracy(spark, d):
    """Accuracy of a language learner on batches that turn from English-French to English-Spanish, under three policies.

    Six batches of 100 + 100 documents, drawn by hash from all documents of their languages (1 200 are needed).
    """
    docs = table(spark, d, "documents").where("length(text) > 0")
    sample = stratified(docs.select("doc_id", "text", "lang"), "lang", {"en": 600, "fr": 300, "es": 300}, ["doc_id"])
    rows = letter_shares(sample).join(sample.select("doc_id", "lang"), "doc_id").orderBy("doc_id").collect()
    x, lang = np.array([r.features for r in rows]), np.array([r.lang for r in rows])
    rng = np.random.default_rng(0)
    pool = {g: np.flatnonzero(lang == g) for g in ("en", "fr", "es")}

    def batch(other: str) -> tuple:
        at = np.concatenate([rng.choice(pool["en"], 100), rng.choice(pool[other], 100)])
        return x[at], (lang[at] == "en").astype(float)

    batches = [batch(o) for o in ("fr", "fr", "fr", "es", "es", "es")]
    names = [f"f{j}" for j in range(26)]
    fit = lambda b: fitting.fit_array(b[0], names, fitting.FitOptions(beta=20, scale="zscore"))
    from ..plans.harness import test_method

    accuracy = lambda m, b: ((np.c_[(b[0] - m[1]) / m[2], np.ones(len(b[0]))] @ m[0] > 0) == b[1]).mean()
    out = []
    for policy in ("retrain", "none", "always"):
        for r in monitor.adapt_loop(batches, fit, lambda b: _logistic(*b), accuracy, lambda h, b: test_method("balanced", h, [b[0]])[0][1], policy):
            out.append((policy, r["batch"], r["drift"], round(r["accuracy"], 6)))
    return spark.createDataFrame(out, "policy string, batch int, drift boolean, accuracy double")


# ------------------------------------------------------------------ pipeline, SQL and source surfaces


@query()
def ml_pipeline_bins(spark, d):
    """Assembler, scaler and balanced bins as one machine-learning pipeline; rows per bin of the whole table."""
    from pyspark.ml import Pipeline
    from pyspark.ml.feature import StandardScaler, VectorAssembler

    li = table(spark, d, "lineitem").select("l_quantity", "l_extendedprice", "l_discount")
    steps = [VectorAssembler(inputCols=li.columns, outputCol="raw"), StandardScaler(inputCol="raw", outputCol="features", withMean=True), BalancedBins(beta=400, kInit=12)]
    return Pipeline(stages=steps).fit(li).transform(li).groupBy("bin").agg(F.count("*").alias("n"))


@query("SELECT (l_quantity > 25)::INTEGER AS bin, count(*) AS n FROM lineitem GROUP BY 1")
def sql_assign_bin(spark, d):
    """assign_bin from SQL, over a registered model that has been stored and read back."""
    path = _shared(spark, "model")
    save(spark, fixed_histogram(["x"], [[0.0], [50.0]]), path, 1)
    save(spark, fixed_histogram(["x"], [[0.0], [50.0]]), path, 2)
    register_all(spark, {"halves": load(spark, path)})
    table(spark, d, "lineitem").createOrReplaceTempView("driftlab_lineitem")
    return spark.sql("SELECT assign_bin(array(l_quantity), 'halves') AS bin, count(*) AS n FROM driftlab_lineitem GROUP BY 1")


@query("SELECT 1000::BIGINT AS n, 500::BIGINT AS moved")
def source_batch(spark, d):
    """The generator as a data source: rows after the change point have a mean near the drift."""
    spark.dataSource.register(DriftSource)
    df = spark.read.format("drift_points").option("rows", 1000).option("drift", 50.0).option("after", 500).load()
    return df.agg(F.count("*").alias("n"), F.count_if(F.col("x1") > 25).alias("moved"))


@query("SELECT 1000::BIGINT AS n, 499500::BIGINT AS ids")
def source_stream(spark, d):
    spark.dataSource.register(DriftSource)
    df = spark.readStream.format("drift_points").option("rows", 1000).load()
    name = f"d_{uuid.uuid4().hex}"
    q = df.writeStream.format("memory").queryName(name).option("checkpointLocation", _shared(spark, "source")).start()
    for _ in range(6):
        q.processAllAvailable()
    q.stop()
    return spark.table(name).agg(F.count("*").alias("n"), F.sum("id").alias("ids"))
