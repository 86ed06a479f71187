"""Clustering by exact score gains, as PySpark DataFrame operators."""
