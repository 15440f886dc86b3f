"""A Spark engine that finds the categories of unlabelled items, and what surrounds it."""
