"""Column functions: time granules and three-valued predicates."""
