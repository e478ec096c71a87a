"""Functions that SQL users can call."""
