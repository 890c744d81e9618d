"""Consensus training with adaptive waiting, as Spark DataFrames."""
