"""Structured Streaming around the methods."""
