"""Readers, writers and the experiment domains."""
