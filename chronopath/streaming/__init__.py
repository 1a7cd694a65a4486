"""Structured Streaming pipelines over evolving edges."""
