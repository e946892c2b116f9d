"""Clustering of large sets of small labeled graphs on Spark."""
