"""Structured Streaming: scoring with fixed centers, windows, deduplication, drift and re-seeding."""
