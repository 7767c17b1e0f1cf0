"""Column expressions: tokens, weights, string similarity, signatures."""
