"""DataFrame operators: primitives, reducer joins, decomposition joins, baselines and the relational operators around them."""
