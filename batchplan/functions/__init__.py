"""Column functions: forward passes, losses and vectors."""
