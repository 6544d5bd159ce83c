"""Samplers, baselines, estimators, measures and applications."""
