"""Operators on DataFrames: filters, chains, baselines, joins that Spark lacks."""
