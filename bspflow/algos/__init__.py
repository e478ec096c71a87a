"""The library of graph methods.  Each takes a graph (or a table) and returns a DataFrame."""
