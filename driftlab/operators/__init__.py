"""Fitting, assigning, testing: the methods and their baselines."""
