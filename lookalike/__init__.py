"""Spark-first search for look-alike graph nodes that a classifier treats differently."""

__version__ = "0.1.0"
