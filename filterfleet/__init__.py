"""Spark engine for all-membership search over many Bloom filters."""
