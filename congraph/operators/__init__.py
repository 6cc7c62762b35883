"""Ways to answer the query of a pattern, and the operators around them."""
