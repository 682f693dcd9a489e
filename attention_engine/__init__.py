"""Implicit-feedback spatial exploration on Spark."""
