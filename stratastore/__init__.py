"""Deduplicating, authenticated content store on Spark DataFrames."""
