"""Measures, splits and experiments."""
