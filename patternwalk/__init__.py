"""Sampled frequent-subgraph mining on Spark."""

__version__ = "0.1.0"
