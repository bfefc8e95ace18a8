"""Predicates, pruning and plan matching."""
