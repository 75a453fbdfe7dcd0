"""Exact triangle counting and local clustering coefficients on Spark."""
