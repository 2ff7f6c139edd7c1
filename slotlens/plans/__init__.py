"""Whole pipelines, accuracy and cost measures."""
