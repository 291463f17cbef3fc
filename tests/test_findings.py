"""Findings of a review: odd rows and larger tables against the SQL of the queries."""

import os

import duckdb
import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from driftlab.operators import fitting
from driftlab.plans.harness import synthetic_sets
from driftlab.queries import load
from driftlab.sources import tables


def written(folder, **tables):
    """Tables given as SQL, as Parquet in a folder."""
    for name, sql in tables.items():
        duckdb.execute(f"COPY ({sql}) TO '{folder}/{name}.parquet' (FORMAT parquet)")
    return str(folder)


def both(spark, name, folder):
    """(rows of the query, rows of its SQL), sorted, to the last bit."""
    queries, oracle = load()
    con = duckdb.connect()
    for f in os.listdir(folder):
        if f.endswith(".parquet"):
            con.execute(f"CREATE VIEW {f.removesuffix('.parquet')} AS SELECT * FROM '{folder}/{f}'")
    con.execute(oracle[name])
    names = [c[0] for c in con.description]
    return sorted(repr([r[c] for c in names]) for r in queries[name](spark, folder).collect()), sorted(repr(list(r)) for r in con.fetchall())


def test_sessions_do_not_come_to_the_driver(spark, sf):
    got = load()[0]["stream_session"](spark, sf)
    assert got.inputFiles() and got.count() > 0


def test_seeding_of_a_large_table(spark):
    """More rows than a fit's sample may have, by joins and by the array kernel: scattered points, and points in copies."""
    rng = np.random.default_rng(1)
    n = fitting.SAMPLE_CAP + 1000
    scattered = (rng.normal(size=(n, 2)) ** 3 * 100_000).astype(int)
    for x in (scattered, np.repeat(scattered[: n // 7], 7, axis=0), np.stack(np.divmod(np.arange(400), 20), axis=1) * 10):
        p = spark.createDataFrame(pd.DataFrame({"id": np.arange(len(x)), "a": x[:, 0], "b": x[:, 1]}))
        got = fitting.seed_table(p, 3, ("a", "b"), rounds=2).toPandas()
        block = fitting.greedy_seed(x, 3)[1]
        for b in range(2):
            assert sorted(got[got["round"] == b].id) == np.flatnonzero(block == b).tolist()


def test_letter_shares_round_as_the_sql(spark, tmp_path):
    """41 of 640 characters are 0.0640625: the nearest double is below it, the printed decimals are a half."""
    d = written(tmp_path, documents="SELECT k AS doc_id, repeat('a', k::INTEGER) || repeat('-', (640 - k)::INTEGER) AS text FROM range(1, 640) t(k) UNION ALL SELECT 0, '' UNION ALL SELECT 1000, NULL")
    for name in ("feat_letters26", "feat_bigrams"):
        got, want = both(spark, name, d)
        assert got == want


def test_newest_events_of_shuffled_rows(spark, tmp_path):
    d = written(tmp_path, events="SELECT k AS event_id, k % 3 AS user_id, TIMESTAMP '2024-01-01' + to_seconds((k * 7919 + k * k) % 1009) AS ts FROM range(900) t(k)")
    got, want = both(spark, "op_lateral_topk", d)
    assert got == want


@pytest.mark.parametrize("name", ["chi2_ppf_grid", "chi2_sf_grid", "cost_formulas", "exp1_partition", "exp2_ranks", "exp2_train_size", "exp2_type1_type2", "exp3_dims", "offset_closed_form", "op_recursive"])
def test_needs_its_table(spark, tmp_path, name):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        load()[0][name](spark, str(tmp_path)).collect()


def test_standard_rows(spark, tmp_path):
    df = spark.range(50).select("id", (F.col("id") * 3).alias("a"), F.lit(7.0).alias("b"))
    got = tables.standard_rows(df, ("a", "b"), ("id",), str(tmp_path))(120).orderBy("id").collect()
    assert [r.id for r in got] == list(range(120)) and got[0][1:] == got[50][1:] == got[100][1:]
    first = sorted(r.u1 for r in got[:50])
    assert np.allclose(first, np.arange(50) / 49) and abs(sum(r.g1 for r in got[:50])) < 1e-9 and all(r.g2 == r.u2 == 0 for r in got)
    sets = synthetic_sets(spark, ["2d-1G-mean"], 1, 40, 20, 2, drift=5.0, source=tables.standard_rows(df, ("a", "b"), ("id",), str(tmp_path / "sets")))
    moved = {r.drifted: r.x for r in sets.groupBy("drifted").agg(F.avg("x2").alias("y"), F.avg("x1").alias("x")).collect()}
    assert moved[True] - moved[False] > 4
