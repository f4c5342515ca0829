"""Column functions: similarities, influence curves, SQL registration."""
