"""Weak-memory time-series analytics on Spark: overlapping blocks, block-local kernels, small reductions."""
