"""Cardinality estimation for graph patterns on Spark."""
