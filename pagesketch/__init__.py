"""Frequency sketches for very large batches and streams, on Spark DataFrames."""
