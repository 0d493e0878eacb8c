"""streaming of the ability-ranking engine."""
