"""Scoring of samples as they arrive."""
