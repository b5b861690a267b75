"""Posterior sampling over shards with slow workers, on Spark DataFrames."""
