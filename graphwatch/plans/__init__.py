"""Cutting patterns, choosing strategies, generating workloads."""
