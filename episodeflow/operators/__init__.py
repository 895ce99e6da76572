"""Counting, candidates, rewriting, significance, similarity and baselines."""
