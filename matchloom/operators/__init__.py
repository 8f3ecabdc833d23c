"""Methods and baselines."""
