"""Clustering of imbalanced data streams on Spark."""
