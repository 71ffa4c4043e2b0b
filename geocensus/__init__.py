"""Measures geospatial content in web-scale text collections, on Spark."""
