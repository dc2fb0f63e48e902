"""Experiments: configurations, their runs and their reports."""
