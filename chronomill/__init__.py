"""Incremental maintenance of metric-temporal rule models on Spark DataFrames."""
