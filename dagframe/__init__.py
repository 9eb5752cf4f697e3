"""Causal-graph learning on Spark: bounds, learners, baselines, measures and monitoring over DataFrames."""

__version__ = "0.1.0"
