"""Readers, planted data and sinks."""
