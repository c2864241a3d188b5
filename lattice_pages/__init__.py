"""Lattice-page analytics: a Spark-native codec for ordered numeric pages."""

__version__ = "0.1.0"
