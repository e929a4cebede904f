"""The parsing steps and the baselines."""
