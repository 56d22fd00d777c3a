"""Boundary-integral analytics as Spark dataframes."""
