"""Relational operators: graphs, models, traversals, baselines, measures."""
