"""Clustering of large document collections, written for Spark."""
