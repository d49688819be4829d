"""Significant spatial co-location mining as Spark plans."""
