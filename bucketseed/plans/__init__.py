"""Whole runs: the estimator, the three-phase plan, and parameter grids."""
