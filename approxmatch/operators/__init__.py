"""Indexes, predicates, selections, joins, evaluation and data generation."""
