"""Structured Streaming forms of the usage features."""
