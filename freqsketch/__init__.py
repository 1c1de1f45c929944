"""Frequency sketching over DataFrames: mergeable counter tables, built and queried in Spark."""
