"""Maintained graph-pattern views over property graphs, on Spark."""
