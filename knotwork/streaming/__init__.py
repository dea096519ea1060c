"""Incremental counts over a stream of edges (an extension)."""
