"""Expressions: ages and time bins, predicates over tuples and births, measures."""
