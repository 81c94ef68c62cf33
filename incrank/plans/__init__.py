"""Graph state, supersteps, methods and experiments."""
