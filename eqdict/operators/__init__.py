"""Building, probing, membership, baselines, measures and applications."""
