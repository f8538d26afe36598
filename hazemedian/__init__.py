"""Uncertain k-median clustering on Spark: nodes, summaries, solvers, streams and measures."""
