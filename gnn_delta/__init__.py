"""Incremental inference of graph neural networks on Spark."""
