"""Distinct-count sketches as ordinary Spark aggregations."""
