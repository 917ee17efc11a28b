"""Births, selections, aggregation, and the executors of cohort plans."""
