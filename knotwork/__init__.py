"""Subgraph-pattern mining on Spark."""
