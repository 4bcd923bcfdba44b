"""Streaming of access weights."""
