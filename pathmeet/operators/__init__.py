"""Methods, variants and baselines of the distance engine."""
