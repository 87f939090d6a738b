"""Data-cube materialization and maintenance on Spark."""
