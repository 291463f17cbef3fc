"""Experiment harness, workloads, cost model and plan reports."""
