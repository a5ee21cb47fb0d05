"""Optimal-split search for decision trees on Spark: exact, sampled and few-pass methods."""
