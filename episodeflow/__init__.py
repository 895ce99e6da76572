"""Frequent episodes in timed event streams, as DataFrame plans."""
