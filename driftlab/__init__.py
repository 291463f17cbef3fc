"""driftlab: distribution-drift detection on Spark DataFrames."""

__version__ = "0.1.0"
