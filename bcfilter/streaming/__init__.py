"""Structured Streaming forms of probing, counting and clearing."""
