"""Iterated plans: refinement, multilevel mapping, multisection, baselines and experiments."""
