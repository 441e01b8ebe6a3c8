"""Exact similarity clustering of element sets by size-tagged sub-signature keys, on Spark."""
