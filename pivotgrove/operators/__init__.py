"""Operators: build, bounds, search, insertion, strategy choice, k-means, generic relational ones."""
