"""plans of the ability-ranking engine."""
