"""Fixed-gap episode compression for event sequences, on Spark DataFrames."""
