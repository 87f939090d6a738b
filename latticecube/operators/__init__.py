"""Materialization, baselines, maintenance, recovery and answering."""
