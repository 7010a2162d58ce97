"""Graph and collection operators, loops, algorithms and baselines."""
