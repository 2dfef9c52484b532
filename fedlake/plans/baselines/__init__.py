"""Baselines: centralised training, neural and factor models, second-order meta-learning, ids only, client graphs."""
