"""Features, pairs, training, scoring and graphs."""
