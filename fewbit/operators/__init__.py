"""DataFrame operators: task builders, the objective, one-vs-all, measures and the relational surface around them."""
