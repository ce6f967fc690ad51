"""The paper's methods, measures and experiments as named queries over the given tables, each beside its SQL twin."""
