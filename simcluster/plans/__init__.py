"""Whole searches, baselines, measures and experiments."""
