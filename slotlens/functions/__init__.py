"""Numeric kernels and functions registered for SQL."""
