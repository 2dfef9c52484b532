"""Training and evaluation plans: kernels, rounds, baselines, attack, experiments."""
