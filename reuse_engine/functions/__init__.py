"""Column functions: dialects, fingerprints, scores."""
