"""Column functions: interval predicates and distances."""
