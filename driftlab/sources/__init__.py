"""Readers, writers, generators, samplers and the histogram store."""
