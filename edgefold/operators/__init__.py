"""Folds, baselines and the relational operators around them."""
