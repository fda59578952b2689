"""Ranking of evolving graphs on Spark DataFrames."""
