"""Matchers that the property-pair classifier is compared with."""
