"""Logistic regression with co-distributed samples and parameters, on Spark DataFrames."""
