"""Trajectory clustering on Spark: series, features, ensemble clustering, baselines and measures."""
