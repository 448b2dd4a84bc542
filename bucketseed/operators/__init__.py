"""Operators: transformation to buckets, seeding, centers, assignment, baselines, measures, uses."""
