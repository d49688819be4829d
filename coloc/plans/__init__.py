"""Whole methods and experiments."""
