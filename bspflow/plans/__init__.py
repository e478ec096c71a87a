"""Builders of the logical and physical plans of a superstep."""
