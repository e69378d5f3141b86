"""Outline engine: section hierarchies of long documents, recovered on Spark."""
