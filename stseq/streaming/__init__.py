"""Structured Streaming forms of the joins, densities and clusters."""
