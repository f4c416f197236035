"""Coded gradient descent over padded device moments, on Spark DataFrames."""
