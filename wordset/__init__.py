"""Exact set intersection on Spark: hashed small groups, word images, planners, baselines and measures."""

__version__ = "0.1.0"
