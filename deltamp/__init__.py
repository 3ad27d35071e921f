"""Incremental message-passing inference on Spark DataFrames."""
