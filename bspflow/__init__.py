"""bspflow: bulk-synchronous vertex programs as relational plans on Spark."""
