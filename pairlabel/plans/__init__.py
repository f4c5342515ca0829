"""Plan choice and experiments."""
