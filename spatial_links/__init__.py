"""Topological link discovery between two sets of lines and polygons, written for Spark DataFrames."""

__version__ = "0.1.0"
