"""Spark-native evaluation of acyclic conjunctions of regular path queries."""

__version__ = "0.1.0"
