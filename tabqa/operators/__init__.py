"""Operators: layout, unfolding, the universal store, dependencies, query answering, measures."""
