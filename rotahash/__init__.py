"""Jaccard sketching for Spark: binned MinHash refilled by one short rotating permutation, its baselines, measures and uses."""
