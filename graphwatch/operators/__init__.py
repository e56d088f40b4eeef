"""Matching, statistics and baselines on edge tables."""
