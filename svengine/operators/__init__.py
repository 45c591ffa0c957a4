"""Registers as DataFrames: construction, gates, executors, measurement."""
