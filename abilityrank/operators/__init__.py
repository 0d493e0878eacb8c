"""operators of the ability-ranking engine."""
