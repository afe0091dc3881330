"""Staged membership filters on Spark: plan, build, store, update and probe set-membership filters as DataFrames."""
