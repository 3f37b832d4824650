"""Column functions: instants, intervals, predicates and user functions."""
