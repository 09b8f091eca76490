"""Statistic-preserving simplification of time series on Spark."""
