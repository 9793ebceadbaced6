"""Column functions: probabilities, costs, tokens, optimisers, names of sub-features."""
