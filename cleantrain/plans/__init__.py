"""Plans that put operators together: fixtures, the cleaning loop, baselines and experiments."""
