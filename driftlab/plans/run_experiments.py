"""python -m driftlab.plans.run_experiments [--runs N] [--tests N] [--sf-dir DIR] [--only exp1,exp2,...]: all experiments, as Markdown tables.

The full protocol is --runs 50 --tests 250. Error tables give mean and sample standard deviation over runs, in percent.
"""

from __future__ import annotations

import argparse
import time
from collections.abc import Sequence

from pyspark.sql import DataFrame

from ..operators import measures
from ..session import local_session
from . import workloads
from .harness import METHODS, run_trials, synthetic_sets


def markdown(rows: Sequence[Sequence], head: Sequence[str]) -> str:
    lines = ["| " + " | ".join(head) + " |", "|" + " --- |" * len(head)]
    return "\n".join(lines + ["| " + " | ".join(str(c) for c in r) + " |" for r in rows])


def error_grid(trials: DataFrame, methods: Sequence[str]) -> str:
    """Workloads down, methods across: Type-I / Type-II errors, and the rank of the average Type-II."""
    trials = trials.persist()
    got = {(r.workload, r.method): r for r in measures.error_table(trials).collect()}
    ranks = {r.method: r for r in measures.error_rank(trials).collect()}
    trials.unpersist()
    show = lambda m, s: f"{m:.1f}" if s is None else f"{m:.1f}±{s:.1f}"
    rows = [[w, *(f"{show(got[w, m].type1, got[w, m].type1_sd)} / {show(got[w, m].type2, got[w, m].type2_sd)}" for m in methods)] for w in sorted({w for w, _ in got})]
    rows.append(["average (rank)", *(f"{ranks[m].type1:.1f} / {ranks[m].type2:.1f} ({ranks[m].rank})" for m in methods)])
    return markdown(rows, ["workload", *methods])


def main() -> None:
    p = argparse.ArgumentParser()
    p.add_argument("--runs", type=int, default=5)
    p.add_argument("--tests", type=int, default=50)
    p.add_argument("--sf-dir", default="/root/testdata/sf0.1")
    p.add_argument("--only", default=",".join(["exp1", "exp2", "slide", "size", "exp3", *(f"exp4_{w}" for w in workloads.SIZES)]))
    p.add_argument("--methods", default=",".join(METHODS), help="methods of exp2 and exp4")
    a = p.parse_args()
    spark = local_session(spark__driver__memory="8g")
    spark.sparkContext.setLogLevel("ERROR")
    histograms = METHODS[:-1]
    methods = a.methods.split(",")
    jobs = {
        "exp1": lambda: markdown([[r.shape, r.method, f"{r.intensity_sd:.4f}", r.min_count, r.max_count] for r in workloads.partition_experiment(spark).collect()], ["shape", "method", "sd of shares", "least", "most"]),
        "exp2": lambda: error_grid(workloads.two_dimensional(spark, a.runs, a.tests, methods=methods), methods),
        "slide": lambda: error_grid(run_trials(synthetic_sets(spark, ["2d-U-mean"], a.runs, tests=a.tests, slide=True), ("x1", "x2"), histograms), histograms),
        "size": lambda: "\n\n".join(error_grid(workloads.training_sizes(spark, runs=a.runs, tests=a.tests, kinds=None, expected=e), ("balanced",)) for e in (True, False)),
        "exp3": lambda: error_grid(workloads.dimensions(spark, runs=max(1, a.runs // 2), tests=a.tests), histograms),
        **{f"exp4_{w}": lambda w=w: error_grid(workloads.document_experiment(spark, a.sf_dir, w, a.runs, a.tests, methods), methods) for w in workloads.SIZES},
    }
    for name in a.only.split(","):
        start = time.perf_counter()
        print(f"## {name}\n\n{jobs[name]()}\n\n{time.perf_counter() - start:.0f} s\n", flush=True)
    spark.stop()


if __name__ == "__main__":
    main()
