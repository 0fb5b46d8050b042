"""Redundancy-encoded distributed optimisation, native to Spark DataFrames."""
