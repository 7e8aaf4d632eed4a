"""Inverted lists from DataFrames, and their compression, on Spark."""
