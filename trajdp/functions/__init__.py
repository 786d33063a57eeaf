"""Column functions: noise, space-filling curves."""
