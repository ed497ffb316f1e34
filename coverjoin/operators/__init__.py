"""Join methods and baselines as DataFrame plans."""
