"""Cohort analysis over user-activity tables on Spark: one algebra, several interchangeable executors."""
