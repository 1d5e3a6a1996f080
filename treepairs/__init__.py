"""Top-k pairs of objects annotated with terms of a tree, for Spark."""
