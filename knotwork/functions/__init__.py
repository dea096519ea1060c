"""Driver-side mathematics of patterns: symmetry, discovery orders and their cost."""
