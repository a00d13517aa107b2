"""Validation of partitioned feature data from small per-partition summaries, built on Spark DataFrames."""
