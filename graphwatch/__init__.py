"""Continuous pattern detection on typed edge streams, for Spark."""
