"""Compiled programs and their Spark executors."""
