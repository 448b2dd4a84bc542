"""Seed-count-free clustering by locality-sensitive buckets, on Spark DataFrames."""
