"""functions of the ability-ranking engine."""
