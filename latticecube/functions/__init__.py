"""Aggregates and column functions."""
