"""Hybrid two-vector search on Spark."""
