"""Cohorts over streams of activities."""
