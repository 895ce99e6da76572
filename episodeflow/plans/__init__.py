"""Which strategy counts, and the level-wise loop."""
