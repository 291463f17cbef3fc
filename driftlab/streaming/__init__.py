"""Drift detection on streams and adaptation."""
