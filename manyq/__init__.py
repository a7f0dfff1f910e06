"""Batches of independent graph queries on Spark."""
