"""propalign: finds which properties of entities from many sources mean the same thing, on Spark."""
