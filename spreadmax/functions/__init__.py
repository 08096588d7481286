"""Column functions: hashes, draws, thresholds, deterministic random numbers."""
