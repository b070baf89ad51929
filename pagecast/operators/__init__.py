"""The predictive operators: grid, page matrix, factors, answers."""
