"""Spark-native distributed optimisation under a communication budget."""

__version__ = "0.1.0"
