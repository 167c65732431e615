"""Column expressions: buckets, fingerprints, distances, gains."""
