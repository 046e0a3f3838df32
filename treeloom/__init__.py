"""Hybrid path and text queries over tree-structured documents, on Spark."""
