"""Subsequence anomalies under drifting normality, on Spark DataFrames."""
