"""Versioned, compressed, streaming graphs on Spark DataFrames: ordered sets cut into hash-delimited chunks."""
