"""sources of the ability-ranking engine."""
