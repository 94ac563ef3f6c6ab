"""Column functions: portable hashing, tokens and features, band radius, student losses."""
