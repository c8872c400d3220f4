"""Sampling without replacement over mini-batches, written for Spark."""
