"""Structured Streaming forms of the operators; the batch forms are the reference."""
