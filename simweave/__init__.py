"""All-pairs similarity joins with Bayesian verification, built on Spark DataFrames."""
