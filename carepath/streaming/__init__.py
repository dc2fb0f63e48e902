"""Structured Streaming forms of the visit and window operators."""
