"""Join operators, baselines, measures and applications."""
