"""Functional low-rank compression of scattered samples on Spark."""
