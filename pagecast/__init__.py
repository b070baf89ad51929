"""Predictive queries over time-series tables, on Spark DataFrames."""
