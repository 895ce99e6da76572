"""Online counting, rates and bursts."""
