"""Accuracy measures over score tables."""
