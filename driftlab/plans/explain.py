"""What a fit tried and what a test's plan does."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame

from ..operators.histogram import EXPRESSION_TERMS, Histogram


def fit_report(hist: Histogram) -> str:
    tried = ", ".join(f"K={k}{' feasible' if ok else ''}" for k, ok in hist.trail) or "nothing tried"
    how = "generated code" if hist.n_bins * hist.n_features <= EXPRESSION_TERMS else "Arrow function"
    return f"{hist.kind}: {hist.n_bins} bins over {hist.n_features} features, theta {hist.theta:g}, counts {int(hist.counts.min())} to {int(hist.counts.max())}; labels by {how}; {tried}"


def physical_plan(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def plan_report(df: DataFrame) -> dict:
    """Counts of exchanges, joins and Python operators, and the scans' columns and pushed filters."""
    text = physical_plan(df)
    return {
        "exchanges": len(re.findall(r"\bExchange\b", text)),
        "broadcasts": text.count("BroadcastExchange"),
        "cartesian": text.count("CartesianProduct"),
        "python": len(re.findall(r"Python|Arrow|Pandas", text)),
        "columns": re.findall(r"ReadSchema: struct<([^>]*)>", text),
        "pushed": re.findall(r"PushedFilters: \[([^\]]*)\]", text),
    }
