"""Encoders, numpy kernels, models and their training inside Spark tasks."""
