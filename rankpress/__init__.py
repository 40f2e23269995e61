"""Predictive text compression as Spark DataFrame operations."""
