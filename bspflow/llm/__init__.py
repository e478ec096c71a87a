"""Training-data operators on Spark DataFrames: deduplication, mixing, search, tokens, privacy, language.

Nothing outside this package imports it.  Each module holds one operator with its own interface;
``queries`` registers the thin digest queries that run the operators over whole tables.
"""
