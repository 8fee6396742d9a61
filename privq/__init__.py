"""Differentially private release of many quantiles of one column, on Spark."""
