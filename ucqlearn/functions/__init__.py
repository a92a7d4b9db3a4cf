"""Column helpers, losses and models."""
