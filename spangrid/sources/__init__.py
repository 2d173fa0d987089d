"""Interval relations derived from the given tables, generated data, query sets, and the saved grid as a data source."""
