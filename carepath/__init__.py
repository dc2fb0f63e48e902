"""Modelling of longitudinal records on Spark: visits, codes, notes, folds, windows, models and measures."""
