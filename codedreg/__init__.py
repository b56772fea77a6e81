"""Coded training of linear models over clients of unequal speed, on Spark DataFrames."""
