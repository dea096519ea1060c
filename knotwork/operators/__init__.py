"""Operators on graphs: building, mining, motif counting, baselines and measures."""
