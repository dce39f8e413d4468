"""Column functions: hashes, segments, divergence terms, size formulas, shingles."""
