"""Novelty and evolution analytics on Spark."""
