"""Incremental profiles and matching over streams."""
